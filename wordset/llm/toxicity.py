"""Toxicity after noisy-channel deobfuscation.

Writers disguise words: digits and signs for letters, letters drawn out, letters set apart. Each disguised spelling
is a lattice: at every character the letters it may stand for, each with the cost of such a disguise, or nothing where a sign
or a repeated letter may be dropped. The cheapest path under a character trigram model, found by Viterbi's algorithm, is the restored
text. Spellings with only letters and no repeats have a single path and are taken as they are, so only odd
tokens are decoded, once per worker each. A letter that stands twice is a lattice of itself and one letter, so that words which are written so stay and others are
restored.

The trigram model is counted over all documents. The classifier reads the words of the restored text, whole and
by their first letters, in a logistic regression on a bounded labelled sample. Words that toxic documents hold far
beyond chance (chi-squared) take part, with weights of zero or more.

Edge cases: null and empty texts have the least score; without any toxic training row every score is that; repeated rows get
equal scores; doc_id may be null; an empty table gives an empty result; very long texts are counted in pieces and scored by their distinct words; other columns
pass through ``accepted`` unchanged, whatever their names.
"""

from __future__ import annotations

import math
import re
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.functions.store import free_name, written
from wordset.functions.worker import column_kernel, on_worker
from wordset.llm.labelled import held_out, training_rows

#: Labelled rows that the classifier is fitted on, at most.
BOUND = 8192
#: A word counts from this chi-squared on; PENALTY is that of the squared weights.
CHI2 = 20.0
PENALTY = 0.1
#: Log-odds of a text without any such word, at most.
LEAST = -1.0
THRESHOLD = 0.7
#: First letters of a word that are features beside the word.
STEMS = (4, 5, 6)

# ---- the character model: 26 letters, 36 places for other letters, 0 for all else
SYMBOLS = 64
OTHER = 63
_PIECE = 1 << 19


def _symbol_table() -> np.ndarray:
    t = np.zeros(0x250, np.uint32)
    for c in range(0x250):
        low = chr(c).lower()[0]
        if "a" <= low <= "z":
            t[c] = ord(low) - 96
        elif low.isalpha():
            t[c] = 27 + (ord(low) & 0x1F) if ord(low) < 0x100 else OTHER
    return t


_TABLE = _symbol_table()


def symbols(text: str) -> np.ndarray:
    code = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    return np.where(code < len(_TABLE), _TABLE[np.minimum(code, len(_TABLE) - 1)], OTHER)


def count_batches(batches):
    """Character trigrams of the texts of a partition: ``code, n``."""
    total = np.zeros(SYMBOLS**3, np.int64)
    for b in batches:
        for t in b.column("text"):
            t = t.as_py()
            before = [0, 0]
            for at in range(0, len(t or ""), _PIECE):
                s = np.r_[before, symbols(t[at : at + _PIECE]), [0] * (at + _PIECE >= len(t))].astype(np.uint32)
                total += np.bincount(s[:-2] << 12 | s[1:-1] << 6 | s[2:], minlength=SYMBOLS**3)
                before = s[-2:]
    code = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(code, pa.int32()), pa.array(total[code])], ["code", "n"])


def trigram_costs(docs: DataFrame) -> np.ndarray:
    """Bits of each character after two others, from all documents, smoothed by bigrams and single characters."""
    rows = docs.select("text").mapInArrow(on_worker(__name__, "count_batches"), "code int, n long").groupBy("code").agg(F.sum("n").alias("n")).toArrow()  # 64^3 rows at most
    n = np.zeros(SYMBOLS**3)
    n[rows["code"].to_numpy()] = rows["n"].to_numpy()
    n = n.reshape(SYMBOLS, SYMBOLS, SYMBOLS)
    one = n.sum((0, 1)) + 0.5
    p1 = one / one.sum()
    two = n.sum(0)
    p2 = (two + 4 * p1) / (two.sum(1, keepdims=True) + 4)
    p3 = (n + 4 * p2) / (n.sum(2, keepdims=True) + 4)
    return -np.log2(p3).astype(np.float32)


# ---- the channel

# Letters that a character is used for, beside itself.
LEET = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "€": "e", "£": "l", "¡": "i", "(": "c",
}
#: Bits that each disguise costs; TWICE is that of one letter written twice.
SWAP, DROP, MASK, REPEAT, TWICE, KEEP = 1.0, 1.0, 5.0, 0.5, 4.0, 14.0
_EDGE = re.compile(r"^[^\w@$!|+€£¡(*]+|[^\w@$+€£]+$")
_SIGN_RUN = re.compile(r"^([^\w])\1+|([^\w])\2+$|[*+|(]+$")
_DRAWN = re.compile(r"([^\W\d_])\1")
_ONE = rf"(?:[^\W\d_]|[{re.escape(''.join(LEET))}])"
_APART = re.compile(rf"(?<![^\W_]){_ONE}(?:[ .\-_*]{{1,3}}{_ONE}){{2,}}(?![^\W_])")


def core(word: str) -> str:
    """The word without the punctuation around it, and without runs of one sign at its ends."""
    word = _SIGN_RUN.sub("", _EDGE.sub("", word))
    return _EDGE.sub("", word)


class Channel:
    """Restores disguised words by Viterbi's algorithm over their lattice."""

    def __init__(self, costs: np.ndarray):
        self.cost = costs.reshape(SYMBOLS * SYMBOLS, SYMBOLS).tolist()

    def options(self, word: str, spaced: bool) -> list[list[tuple[str, float]]]:
        out, i = [], 0
        while i < len(word):
            c, j = word[i], i + 1
            while j < len(word) and word[j] == c:
                j += 1
            run = j - i
            if c.isalpha():
                if run == 1:
                    out.append([(c, 0.0)])
                elif run == 2:
                    out.append([(c + c, 0.0), (c, TWICE)])
                else:  # drawn out: one letter or two are meant
                    out.append([(c, REPEAT), (c + c, 2 * REPEAT)])
            else:
                may = [(x * k, SWAP * min(run, 2)) for x in LEET.get(c, "") for k in range(1 if run > 1 else run, 2 if run > 2 else run + 1)]
                if c == "*" and run <= 2:
                    may += [(chr(k), MASK) for k in range(97, 123)] if run == 1 else []
                if not c.isalnum():
                    may.append(("", DROP * min(run, 2) + (0 if not spaced else -DROP)))
                    if spaced and run >= 2 or spaced and c == " ":
                        may.append((" ", 2.0))
                may.append((c * run, KEEP))
                out.append(may)
            i = j
        return out

    def restore(self, word: str, spaced: bool = False) -> str:
        cost, table = self.cost, _TABLE
        paths: dict[int, tuple[float, str]] = {0: (0.0, "")}  # by the last two symbols
        size = len(table)
        done: list[str] = []
        for may in self.options(word, spaced):
            after: dict[int, tuple[float, str]] = {}
            for state, (spent, said) in paths.items():
                for text, extra in may:
                    s, total = state, spent + extra
                    for c in text:
                        k = ord(c)
                        y = int(table[k]) if k < size else OTHER
                        total += cost[s][y]
                        s = (s & 63) << 6 | y
                    if s not in after or total < after[s][0]:
                        after[s] = (total, said + text)
            paths = after
            if len(paths) == 1 and len(next(iter(paths.values()))[1]) > 64:  # all paths agree so far
                ((s, (total, said)),) = paths.items()
                done.append(said)
                paths = {s: (total, "")}
        end = min(paths.items(), key=lambda p: (p[1][0] + cost[p[0]][0], p[1][1]))
        return "".join(done) + end[1][1]

    def words(self, word: str) -> list[str]:
        """The word as it is meant: restored where its spelling is odd."""
        bare = core(word)
        if bare.isalpha():
            return [self.restore(bare)] if _DRAWN.search(bare) else [bare]
        if not any(map(str.isalpha, bare)):
            return []
        return re.findall(r"[^\W\d_]+", self.restore(bare))

    def apart(self, text: str) -> list[str]:
        """Words whose letters are set apart, as in ``i d i o t``."""
        return [w for m in _APART.finditer(text) for w in re.findall(r"[^\W\d_]+", self.restore(m[0], True))]


def word_features(word: str) -> list[str]:
    return [word, *(word[:k] + "-" for k in STEMS if len(word) > k)]


def restored(text: str | None, channel: Channel) -> str:
    """The text in lower case with odd spellings restored."""
    low = _APART.sub(lambda m: channel.restore(m[0], True), (text or "").lower())
    return re.sub(r"\S+", lambda m: m[0] if core(m[0]).isalpha() and not _DRAWN.search(m[0]) else " ".join(channel.words(m[0])) or m[0], low)


def restore_array(texts: pa.Array, costs) -> pa.Array:
    channel = _channel(costs)
    return pa.array([restored(t.as_py(), channel) for t in texts], pa.string())


_cache: dict = {}


def _channel(costs) -> Channel:
    name, table = costs
    if _cache.get("costs") != name:
        _cache.clear()
        _cache["costs"], _cache["channel"] = name, Channel(table.value)
    return _cache["channel"]


def _shared(spark, value):
    """A broadcast value and a name for it, by which workers keep what they derive from it."""
    return uuid.uuid4().hex, spark.sparkContext.broadcast(value)


def deobfuscated(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` with one more column, ``restored_text``; if there is one of that name, underscores are put before the new one's."""
    costs = _shared(docs.sparkSession, trigram_costs(docs))
    return docs.withColumn(free_name(docs, "restored_text"), column_kernel(__name__, "restore_array", "string", costs)(F.col("text")))


# ---- the classifier


def sample_batches(batches, costs):
    """``y, features`` of labelled rows."""
    channel = _channel(costs)
    for b in batches:
        said = []
        for t in b.column("text"):
            low = (t.as_py() or "").lower()
            words = {w for x in set(low.split()) for w in channel.words(x)} | set(channel.apart(low))
            said.append(sorted({f for w in words for f in word_features(w)}))
        yield pa.RecordBatch.from_arrays([b.column("y"), pa.array(said, pa.list_(pa.string()))], ["y", "features"])


def fit(docs: DataFrame, labels: DataFrame, costs, bound: int = BOUND) -> tuple[float, dict[str, float]]:
    """Intercept and weight of each feature."""
    sampled = training_rows(docs, labels, "toxic", bound).mapInArrow(on_worker(__name__, "sample_batches", costs), "y int, features array<string>")
    rows = written(sampled.withColumn("row", F.monotonically_increasing_id()), "toxic-rows")
    toxic, total = rows.agg(F.coalesce(F.sum("y"), F.lit(0)), F.count(F.lit(1))).first()
    if not toxic:
        return LEAST, {}
    base = toxic / total
    words = rows.select("row", "y", F.explode("features").alias("f"))
    counts = words.groupBy("f").agg(F.sum("y").alias("t"), F.count(F.lit(1)).alias("n"))
    expected = F.col("n") * base
    chi2 = F.pow(F.col("t") - expected, 2) / (expected * (1 - base) + 1e-9)
    telling = counts.filter((F.col("t") >= 3) & (2 * F.col("t") >= F.col("n")) & (chi2 >= CHI2)).select("f")  # of a bounded sample
    found = words.join(F.broadcast(telling), "f").orderBy("row", "f").toArrow()
    return logistic(found["row"].to_pylist(), found["f"].to_pylist(), found["y"].to_numpy(), toxic, total)


def logistic(row: list[int], feature: list[str], y: np.ndarray, toxic: int, total: int) -> tuple[float, dict[str, float]]:
    """Logistic regression with weights of zero or more, by accelerated projected gradients.

    Rows without any feature are known by their number. The penalty shares what several words explain: words that
    only copies of one toxic document have in common get little beside those that many documents have."""
    names, col = np.unique(np.array(feature, dtype=object).astype(str), return_inverse=True)
    ids, at = np.unique(np.array(row, np.int64), return_inverse=True)
    label = np.zeros(len(ids))
    label[at] = y
    plain_toxic = toxic - label.sum()
    plain = total - len(ids)
    w, bias = np.zeros(len(names)), np.log((toxic + 1) / (total - toxic + 1))
    v, v_bias, t = w.copy(), bias, 1.0
    step = 4 / (PENALTY + np.bincount(at, minlength=len(ids)).max(initial=1) * 40 + 0.01 * total)
    for _ in range(3000):
        p = 1 / (1 + np.exp(-(v_bias + np.bincount(at, v[col], len(ids)))))
        p0 = 1 / (1 + np.exp(-v_bias))
        grad = np.bincount(col, (p - label)[at], len(names)) + PENALTY * v
        grad_bias = (p - label).sum() + plain * p0 - plain_toxic
        new, new_bias = np.maximum(v - step * grad, 0), v_bias - step * grad_bias * 0.1
        after = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, v_bias = new + (t - 1) / after * (new - w), new_bias + (t - 1) / after * (new_bias - bias)
        if ((v - new) @ (new - w)) > 0 and grad @ (new - w) > 0:
            t, v, v_bias = 1.0, new.copy(), new_bias  # restart the momentum where it overshoots
        else:
            t = after
        w, bias = new, new_bias
    # the log-odds of the threshold lie in the middle of the gap that parts the sample best, the widest of such gaps
    said = np.r_[np.bincount(at, w[col], len(ids)), 0.0]
    weigh = np.c_[np.r_[label, plain_toxic], np.r_[1 - label, plain - plain_toxic]]
    level, place = np.unique(said, return_inverse=True)
    part = np.c_[np.bincount(place, weigh[:, 0]), np.bincount(place, weigh[:, 1])]
    wrong = np.cumsum(part[:, 0])[:-1] + part[::-1, 1].cumsum()[::-1][1:]
    if len(wrong):
        gaps = np.diff(level)
        k = max(np.flatnonzero(wrong == wrong.min()), key=lambda i: gaps[i])
        bias = min(LEAST, math.log(THRESHOLD / (1 - THRESHOLD)) - (level[k] + level[k + 1]) / 2)
    return float(bias), {f: float(x) for f, x in zip(names.tolist(), w, strict=True) if x > 0.05}


class _Weights(dict):
    """Word as written -> features of the model that it brings."""

    KEPT = 400_000

    def __init__(self, channel: Channel, model: dict[str, float]):
        self.channel, self.model = channel, model

    def __missing__(self, word: str) -> tuple[str, ...]:
        found = tuple(f for w in self.channel.words(word) for f in word_features(w) if f in self.model)
        if len(self) >= self.KEPT:
            self.clear()
        if len(word) <= 64:
            self[word] = found
        return found


def score_array(texts: pa.Array, costs, model) -> pa.Array:
    channel = _channel(costs)
    name, fitted = model
    bias, weight = fitted.value
    if _cache.get("model") != name:
        _cache["model"], _cache["weights"] = name, _Weights(channel, weight)
    weights = _cache["weights"]
    out = []
    for t in texts:
        low = (t.as_py() or "").lower()
        said: set[str] = set()
        for found in filter(None, map(weights.__getitem__, set(low.split()))):
            said.update(found)
        for w in channel.apart(low):
            said.update(f for f in word_features(w) if f in weight)
        out.append(1 / (1 + math.exp(-bias - sum(weight[f] for f in sorted(said)))))
    return pa.array(out, pa.float64())


def with_score(docs: DataFrame, labels: DataFrame, bound: int = BOUND) -> DataFrame:
    """The rows of ``docs`` as a struct ``row``, and their ``score``; only the text goes to Python."""
    costs = _shared(docs.sparkSession, trigram_costs(docs))
    model = _shared(docs.sparkSession, fit(docs, labels, costs, bound))
    return docs.select(F.struct("*").alias("row"), column_kernel(__name__, "score_array", "double", costs, model)(F.col("text")).alias("score"))


def scored(docs: DataFrame, labels: DataFrame, bound: int = BOUND) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every document."""
    out = with_score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), labels, bound)
    return out.select("row.doc_id", held_out(F.col("row.doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def accepted(docs: DataFrame, labels: DataFrame, bound: int = BOUND) -> DataFrame:
    """The rows of ``docs`` that score below the threshold, judged where they are read."""
    return with_score(docs, labels, bound).filter(F.col("score") < THRESHOLD).select("row.*")
