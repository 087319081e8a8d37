"""Quality rules as a bitmask ledger.

One pass takes every measurement of a text. Each rule is one integer comparison of measurements and owns one
bit; the ledger keeps measurements and failure bits of all documents. Policies are named, versioned masks over the bits, so
another policy, or the effect of leaving a rule out, is read off the ledger by bitwise operations, without the texts.

Edge cases: null and empty texts have no words and fail ``few_words``; repeated rows are judged each; an empty table
gives an empty ledger; doc_id may be null; very long texts are measured whole, in memory in proportion to their length; other columns pass through ``accepted`` unchanged,
whatever their names.
"""

from __future__ import annotations

import re
from collections import Counter
from operator import eq

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wordset.functions.worker import column_kernel

WINDOW = 8
BLANKS = b" \t\n\x0b\x0c\r"
SYMBOLS = b"#*$%&|<>"
UPPER = bytes(range(65, 91))
LETTERS = UPPER + bytes(range(97, 123))
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_letters", "n_shouts", "n_stutters", "top_count")

#: Bit -> name and condition of failure, over the measures. A rule never changes its bit; new rules get new bits.
RULES: dict[int, tuple[str, str]] = {
    0: ("few_words", "n_words < 20"),
    1: ("repeated_windows", "100 * n_repeat_words > 30 * n_words"),
    2: ("symbols", "10 * n_symbols > n_words"),
    3: ("repeated_lines", "n_dup_lines >= 3 and 10 * n_dup_lines > 3 * n_lines"),
    4: ("capitals", "10 * n_upper > 6 * n_letters"),
    5: ("exclamations", "10 * n_shouts > 3 * n_words"),
    6: ("stutter", "10 * n_stutters > 3 * n_words"),
    7: ("one_word", "10 * top_count > 4 * n_words"),
    8: ("word_length", "word_chars < 2 * n_words or word_chars > 30 * n_words"),
}
#: Policy -> bits that reject a document.
POLICIES: dict[str, tuple[int, ...]] = {"base_v1": (0, 1), "strict_v1": tuple(RULES)}


def _deleted(b: bytes, chars: bytes) -> int:
    return len(b) - len(b.translate(None, chars))


def repeat_words(words: list[bytes]) -> int:
    """Words that lie in a window of WINDOW words that occurs twice or more."""
    if len(words) <= WINDOW:
        return 0
    joined = b" ".join(words)
    n = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(n + 1) - 1
    starts = (ends - n)[: len(words) - WINDOW + 1].tolist()
    ends = ends[WINDOW - 1 :].tolist()
    h = xxhash.xxh64_intdigest
    codes = np.array([h(joined[a:b]) for a, b in zip(starts, ends, strict=True)], np.uint64)
    order = np.argsort(codes, kind="stable")
    twin = codes[order][1:] == codes[order][:-1]
    if not twin.any():
        return 0
    again = order[np.r_[twin, False] | np.r_[False, twin]].tolist()
    counts = Counter(joined[starts[i] : ends[i]] for i in again)  # equal hashes are checked on the words
    hit = np.zeros(len(words) + 1, np.int64)
    for i in again:
        if counts[joined[starts[i] : ends[i]]] > 1:
            hit[i] += 1
            hit[i + WINDOW] -= 1
    return int((np.cumsum(hit)[:-1] > 0).sum())


def measure(text: str | None) -> tuple[int, ...]:
    text = text or ""
    b = text.encode()
    words = b.split()
    seen: set[bytes] = set()
    dup = 0
    lines = [x for x in b.split(b"\n") if x.strip(BLANKS)]
    for line in lines:
        dup += line in seen
        seen.add(line)
    top = max(Counter(words).values(), default=0)
    return (
        len(words),
        len(text) - _deleted(b, BLANKS),
        _deleted(b, SYMBOLS),
        dup,
        repeat_words(words),
        len(lines),
        _deleted(b, UPPER),
        _deleted(b, LETTERS),
        b.count(b"!!"),
        sum(map(eq, words, words[1:])),
        top,
    )


def measure_array(texts: pa.Array) -> pa.Array:
    rows = np.array([measure(t.as_py()) for t in texts], np.int64).reshape(len(texts), len(MEASURES))
    return pa.StructArray.from_arrays([pa.array(c) for c in rows.T], names=list(MEASURES))


def measured(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` as a struct ``row``, and a struct ``m`` of all measures of their text."""
    return docs.select(F.struct("*").alias("row"), column_kernel(__name__, "measure_array", ", ".join(f"{m} long" for m in MEASURES))(F.col("text")).alias("m"))


def ledger(docs: DataFrame) -> DataFrame:
    """``doc_id``, the measures and ``failed_bits`` of every document."""
    out = measured(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")).select("row.doc_id", "m.*")
    return out.withColumn("failed_bits", failed_bits())


def failed_bits(prefix: str = "") -> Column:
    """All rules, each evaluated once, as one bit each; ``prefix`` is that of the measures' names."""
    bits = F.lit(0).cast("long")
    for bit, (_, condition) in RULES.items():
        condition = re.sub(r"[a-z_]*_[a-z_]+", lambda m: prefix + m[0], condition)
        bits = bits.bitwiseOR(F.when(F.expr(condition), F.lit(1 << bit)).otherwise(F.lit(0)).cast("long"))
    return bits


def mask(policy: str) -> int:
    return sum(1 << b for b in POLICIES[policy])


def passes(policy: str, bits: str = "failed_bits") -> Column:
    return F.col(bits).bitwiseAND(F.lit(mask(policy))) == 0


def ablations(book: DataFrame, policy: str = "strict_v1") -> DataFrame:
    """Per rule of the policy: documents that fail it, and those that only it rejects, from the bits alone."""
    m = mask(policy)
    counts = book.groupBy(F.col("failed_bits").bitwiseAND(F.lit(m)).alias("bits")).agg(F.count(F.lit(1)).alias("n"))
    return counts.select("n", "bits", F.explode(F.array(*(F.struct(F.lit(b).alias("bit"), F.lit(RULES[b][0]).alias("rule")) for b in POLICIES[policy]))).alias("r")).groupBy("r.bit", "r.rule").agg(
        F.sum(F.when(F.expr("(bits & shiftleft(1L, r.bit)) <> 0"), F.col("n")).otherwise(0)).alias("failed"),
        F.sum(F.when(F.expr("bits = shiftleft(1L, r.bit)"), F.col("n")).otherwise(0)).alias("only_this"),
        F.sum(F.when(F.expr("(bits & ~shiftleft(1L, r.bit)) = 0"), F.col("n")).otherwise(0)).alias("kept_without"),
    )


def accepted(docs: DataFrame, policy: str = "strict_v1") -> DataFrame:
    """The rows of ``docs`` that pass, judged where they are read; only the text goes to Python and nothing is joined."""
    return measured(docs).filter(failed_bits("m.").bitwiseAND(F.lit(mask(policy))) == 0).select("row.*")


SQL = r"""
with d as (select doc_id, coalesce(text, '') as t, row_number() over () as rid from documents),
w as (select *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') as ws, string_split(t, chr(10)) as ls from d),
base as (select rid, doc_id, len(ws) as n_words, length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) as word_chars,
  length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) as n_symbols,
  length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')) as n_upper, length(t) - length(regexp_replace(t, '[A-Za-z]', '', 'g')) as n_letters,
  (length(t) - length(replace(t, '!!', ''))) // 2 as n_shouts from w),
lines as (select rid, l from (select rid, unnest(ls) as l from w) where regexp_matches(l, '[^\x20\x09-\x0D]')),
dup as (select rid, sum(n)::bigint as n_lines, sum(n - 1)::bigint as n_dup_lines from (select rid, l, count(*) as n from lines group by all) group by rid),
pos as (select rid, unnest(ws) as word, generate_subscripts(ws, 1) as i from w),
top as (select rid, max(n) as top_count from (select rid, word, count(*) as n from pos group by all) group by rid),
nx as (select rid, i, word, lead(word) over (partition by rid order by i) as next from pos),
st as (select rid, count(*) as n_stutters from nx where word = next group by rid),
win as (select rid, i, array_to_string(list(word) over (partition by rid order by i rows between current row and 7 following), ' ') as g,
  count(*) over (partition by rid order by i rows between current row and 7 following) as k from pos),
rep as (select rid, i, count(*) over (partition by rid, g) as n from win where k = 8),
hit as (select rid, count(distinct p) as n_repeat_words from (select rid, unnest(range(i, i + 8)) as p from rep where n > 1) group by rid),
m as (select doc_id, n_words::bigint as n_words, word_chars::bigint as word_chars, n_symbols::bigint as n_symbols, n_upper, n_letters, n_shouts,
  coalesce(n_lines, 0) as n_lines, coalesce(n_dup_lines, 0)::bigint as n_dup_lines, coalesce(n_repeat_words, 0)::bigint as n_repeat_words,
  coalesce(n_stutters, 0) as n_stutters, coalesce(top_count, 0) as top_count
  from base left join dup using (rid) left join top using (rid) left join st using (rid) left join hit using (rid))
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, ({base}) as base_failed, not ({strict}) as kept from m"""


def oracle() -> str:
    either = lambda policy: " or ".join(f"({RULES[b][1]})" for b in POLICIES[policy])
    return SQL.replace("{base}", either("base_v1")).replace("{strict}", either("strict_v1"))
