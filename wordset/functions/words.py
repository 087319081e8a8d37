"""Small sets as words: images of groups, their intersection and their members."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from wordset.config import Cfg


def word_of(y: Column) -> Column:
    """Aggregate: the word whose bits are the values y, 0 to 63."""
    return F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), y.cast("int")))


def image(y: str, k: int, cfg: Cfg) -> Column:
    """Aggregate: word k of the image of hash values y."""
    if cfg.words == 1:
        return F.expr(f"bit_or(shiftleft(1L, {y}))")
    return F.expr(f"bit_or(case when {y} div 64 = {k} then shiftleft(1L, cast({y} % 64 as int)) else 0L end)")


def image_aggregates(cfg: Cfg, m: int | None = None) -> list[Column]:
    """Aggregates over y_1 ... y_m for all words of all images."""
    return [image(f"y_{j}", k, cfg).alias(name) for j, names in enumerate(cfg.images(m), 1) for k, name in enumerate(names)]


def image_pandas():
    """A grouped Pandas aggregate that makes the same word as ``word_of``, for plans that hold pandas data already."""
    import pandas as pd

    def made(y):
        word = 0
        for v in y.unique().tolist():
            word |= 1 << v
        return word - (1 << 64) if word >> 63 else word

    made.__annotations__ = {"y": pd.Series, "return": int}  # types, not their names
    return F.pandas_udf(made, "long")


def images_meet(left: str, right: str, cfg: Cfg, m: int) -> Column:
    """Whether every one of the m images of the two sides has a bit in common; columns are prefixed by the sides."""
    return reduce(lambda a, b: a & b, (reduce(lambda a, b: a | b, (F.col(left + c).bitwiseAND(F.col(right + c)) != 0 for c in names)) for names in cfg.images(m)))


def any_zero(prefix: str, cfg: Cfg, m: int) -> Column:
    """Whether some image under ``prefix`` is zero in all its words."""
    return reduce(lambda a, b: a | b, (reduce(lambda a, b: a & b, (F.col(prefix + c) == 0 for c in names)) for names in cfg.images(m)))


def bits_of(word: Column, w: int = 64) -> Column:
    """The members of a word, ascending."""
    return F.filter(F.sequence(F.lit(0), F.lit(w - 1)), lambda y: F.getbit(word, y) == 1)


def gamma_bits(x: str) -> str:
    """SQL: length of the Elias gamma code of x >= 1."""
    return f"(2 * (length(bin({x})) - 1) + 1)"


def delta_bits(x: str) -> str:
    """SQL: length of the Elias delta code of x >= 1."""
    return f"(length(bin({x})) - 1 + 2 * (length(bin(length(bin({x})))) - 1) + 1)"
