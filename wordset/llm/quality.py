"""Quality by nearest-neighbour voting in a latent-semantic space.

A text is the distribution of its hashed byte trigrams (case, marks and spacing count) and a few ratios of
repetition. Frequencies are damped by a square root and weighted by inverse document frequency; a singular value decomposition of the labelled rows
gives the latent space. The labelled vectors, at most BOUND rows of RANK numbers, are broadcast; every document's
vector is multiplied with all of them, block by block, so the cosines are exact, and its nearest neighbours vote with
their similarity as weight.

The model is fitted on at most BOUND labelled rows; every document is scored by the same model at any size.

Edge cases: null and empty texts have a score as well (the vector of an empty text); without any labelled row the score
is 0.5, with one label only it is that label; repeated rows get equal scores; doc_id may be null; an empty table gives an empty result; of neighbours
that are equally near at the last place all vote; very long texts are read in pieces; other columns play no part, whatever their names.
"""

from __future__ import annotations

from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.functions.store import written
from wordset.functions.worker import on_worker
from wordset.llm.labelled import held_out, training_rows

#: Labelled rows that the model is fitted on, at most.
BOUND = 4096
BUCKETS = 2048
RATIOS = 4
RANK = 64
NEIGHBOURS = 15
BLOCK = 512
_PIECE = 1 << 20


def features(text: str | None) -> np.ndarray:
    """Square roots of the relative frequencies of hashed byte trigrams, then ratios of repetition."""
    b = (text or "").encode()
    out = np.zeros(BUCKETS + RATIOS, np.float32)
    counts = np.zeros(BUCKETS, np.int64)
    for at in range(0, max(len(b) - 2, 0), _PIECE):  # bounded memory for very long texts
        x = np.frombuffer(b[at : at + _PIECE + 2], np.uint8).astype(np.uint32)
        code = (x[:-2] << 16 | x[1:-1] << 8 | x[2:]) * np.uint32(2654435761)
        counts += np.bincount(code >> np.uint32(21), minlength=BUCKETS)
    if n := counts.sum():
        out[:BUCKETS] = np.sqrt(counts / n)
    words = b.split()
    lines = [x for x in b.split(b"\n") if x]
    if words:
        half = words[: len(words) // 2]
        out[BUCKETS:] = (
            sum(map(eq, words, words[1:])) / len(words),
            1 - len(set(lines)) / max(1, len(lines)),
            1 - len(set(words)) / len(words) if len(words) > 1 else 0,
            1 / (1 + len(half)),
        )
    return out


def feature_batches(batches):
    for b in batches:
        for at in range(0, b.num_rows, BLOCK):
            part = b.slice(at, BLOCK)
            yield pa.RecordBatch.from_arrays([pa.array([features(t.as_py()).tobytes() for t in part.column("text")], pa.binary()), part.column("y")], ["x", "y"])


class Model:
    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.y = y.astype(np.float32)
        if len(x) < 2:
            self.projection = None
            return
        idf = np.log((1 + len(x)) / (1 + (x > 0).sum(0))).astype(np.float32) + 0.1
        idf[BUCKETS:] = 1
        w = x * idf
        self.mean = w.mean(0)
        c = w - self.mean
        rank = min(RANK, len(x) - 1)
        # randomised range finder with power steps; seeded, so a second fit gives the same space
        q = np.linalg.qr(c @ np.random.default_rng(7).standard_normal((c.shape[1], min(rank + 16, len(x))), np.float32))[0]
        for _ in range(3):
            q = np.linalg.qr(c @ np.linalg.qr(c.T @ q)[0])[0]
        v = np.linalg.svd(q.T @ c, full_matrices=False)[2][:rank]
        self.projection = np.ascontiguousarray((v * idf).T, np.float32)
        self.offset = (self.mean @ v.T).astype(np.float32)
        self.points = self._unit(x)

    def _unit(self, x: np.ndarray) -> np.ndarray:
        z = x @ self.projection - self.offset
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.projection is None:
            return np.full(len(x), self.y.mean() if len(self.y) else 0.5)
        cos = self._unit(x) @ self.points.T
        k = min(NEIGHBOURS, len(self.y))
        last = np.partition(cos, len(self.y) - k, axis=1)[:, len(self.y) - k, None]
        row, near = np.nonzero(cos >= last)  # whoever is as near as the last one votes as well
        weight = np.maximum(cos[row, near], 1e-6).astype(np.float64) ** 4
        return np.bincount(row, weight * self.y[near], len(x)) / np.bincount(row, weight, len(x))


def fit(docs: DataFrame, labels: DataFrame, bound: int = BOUND) -> Model:
    rows = written(training_rows(docs, labels, "quality", bound).mapInArrow(on_worker(__name__, "feature_batches"), "x binary, y int"), "quality-rows").orderBy(F.xxhash64("x"), "y").toArrow()
    x = np.frombuffer(b"".join(rows["x"].to_pylist()), np.float32).reshape(-1, BUCKETS + RATIOS)
    return Model(x, rows["y"].to_numpy())


def score_batches(batches, model):
    m = model.value
    for b in batches:
        for at in range(0, b.num_rows, BLOCK):
            part = b.slice(at, BLOCK)
            x = np.stack([features(t.as_py()) for t in part.column("text")])
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(m.score(x).astype(np.float64))], ["doc_id", "score"])


def scored(docs: DataFrame, labels: DataFrame, bound: int = BOUND) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every document."""
    model = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, bound))
    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(on_worker(__name__, "score_batches", model), "doc_id long, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
