"""SQL over set indexes: functions that Catalyst sees through, a table function, and one statement."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import words
from wordset.plans import api

_indexes: dict[str, api.SetIndex] = {}


def register(spark: SparkSession, cfg: Cfg = Cfg()) -> None:
    """Temporary SQL functions ``image_and, prefix_of, t_scan, gamma_bits, delta_bits`` and table functions ``bits_of`` and
    ``intersect_sets``."""
    sql = {
        "image_and(a bigint, b bigint) returns bigint": "a & b",
        "prefix_of(g bigint, t int) returns bigint": f"case when t = 0 then 0L else shiftrightunsigned(g, {cfg.universe_bits} - t) end",
        "t_scan(n bigint) returns int": f"case when (n + {cfg.root - 1}) div {cfg.root} <= 1 then 0 else length(bin((n + {cfg.root - 1}) div {cfg.root} - 1)) end",
        "gamma_bits(x bigint) returns int": words.gamma_bits("x"),
        "delta_bits(x bigint) returns int": words.delta_bits("x"),
    }
    for head, body in sql.items():
        spark.sql(f"create or replace temporary function {head} return {body}")

    @F.udtf(returnType="y int")
    class BitsOf:
        def eval(self, word: int):
            word &= (1 << 64) - 1
            while word:
                low = word & -word
                yield (low.bit_length() - 1,)
                word ^= low

    @F.udtf(returnType="elem bigint")
    class IntersectSets:
        """Common elements of small sets that are given as arrays."""

        def eval(self, lists: list):
            common = set(lists[0]).intersection(*lists[1:]) if lists else set()
            for x in sorted(common):
                yield (x,)

    spark.udtf.register("bits_of", BitsOf)
    spark.udtf.register("intersect_sets", IntersectSets)


def name_index(name: str, index: api.SetIndex) -> None:
    _indexes[name] = index


_STATEMENT = re.compile(r"\s*INTERSECT\s+SETS\s+(?P<sets>.+?)\s+IN\s+(?P<index>\w+)(?:\s+USING\s+(?P<method>\w+))?(?:\s+LIMIT\s+(?P<limit>\d+))?\s*;?\s*", re.I | re.S)


def sql(text: str) -> DataFrame:
    """``INTERSECT SETS a, 'b c' IN index [USING method] [LIMIT n]``."""
    m = _STATEMENT.fullmatch(text)
    if not m:
        raise ValueError("expected: INTERSECT SETS a, b IN index [USING method] [LIMIT n]")
    if m["index"] not in _indexes:
        raise ValueError(f"no index is named {m['index']}")
    names = [a or b for a, b in re.findall(r"'([^']*)'|([^\s,]+)", m["sets"])]
    out = api.intersect(_indexes[m["index"]], names, (m["method"] or "auto").lower())
    return out.limit(int(m["limit"])) if m["limit"] else out


def image_overlaps(a: str, b: str) -> F.Column:
    """Whether two image words have a bit in common."""
    return F.col(a).bitwiseAND(F.col(b)) != 0


def ranges_overlap(a_inf: str, a_sup: str, b_inf: str, b_sup: str) -> F.Column:
    return (F.col(a_inf) <= F.col(b_sup)) & (F.col(b_inf) <= F.col(a_sup))
