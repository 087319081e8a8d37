"""Packing by best-fit decreasing.

Documents are encoded and closed by one separator id. Full windows are cut off the front of overlong documents and
are sequences as they are. The remainders, longest first, go each into the open window with the least room that
still takes them; a segment tree over the remaining capacity finds it in logarithmic time.

Encoding gives the full windows and a table of remainders, one short row per document and no text. These rows are dealt
round to bins of at most 2^19, and every bin is packed by itself in a fixed order: what a bin wastes is part of its last windows, so
padding does not depend on how the documents lie in files, and no row goes to a bin by its content, so repeated rows
make none larger. A task run again gives the same sequences.

Edge cases: null and empty texts are the separator alone; repeated rows are packed each; an empty table gives no
pieces; doc_id may be null; of equally long remainders the one with the least doc_id, start and checksum is placed first, a null doc_id last; very long texts are full
windows and one remainder; other columns play no part, whatever their names. A vocabulary file that splits texts in another way is refused.
"""

from __future__ import annotations

import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.functions.store import written
from wordset.functions.worker import on_worker
from wordset.llm import bpe

WINDOW = 1024
SEPARATOR = 0
_SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
#: Bits of a sequence_id that count within a partition; the bit that tells a bin's sequences from full windows.
LOCAL_BITS, BIN_BIT = 36, 62
#: Remainders in a bin: no more than the last, so that a task's memory is bounded, and no fewer than the first for the sake of more tasks.
FEWEST, MOST = 1 << 14, 1 << 19


class TightestFit:
    """Open windows by remaining capacity: ``take(n)`` gives the window with the least room of n or more, or None."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.windows: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.any = bytearray(2 * self.size)  # whether a node's capacities have a window

    def put(self, room: int, window: int) -> None:
        self.windows[room].append(window)
        i = self.size + room
        while i and not self.any[i]:
            self.any[i] = 1
            i >>= 1

    def take(self, need: int) -> tuple[int, int] | None:
        i = self.size + need
        if not self.any[i]:
            while i > 1 and (i & 1 or not self.any[i + 1]):  # up, until there is something to the right
                i >>= 1
            if i <= 1:
                return None
            i += 1
            while i < self.size:  # down, to the left where possible
                i = 2 * i if self.any[2 * i] else 2 * i + 1
        room = i - self.size
        window = self.windows[room].pop()
        if not self.windows[room]:
            self.any[i] = 0
            i >>= 1
            while i and not (self.any[2 * i] or self.any[2 * i + 1]):
                self.any[i] = 0
                i >>= 1
        return room, window


def best_fit(lengths: list[int], window: int, first: int = 0) -> list[tuple[int, int]]:
    """Window and offset for each length, windows numbered from ``first``."""
    fit, out, new = TightestFit(window), [(0, 0)] * len(lengths), first
    for k in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        n = lengths[k]
        if (found := fit.take(n)) is None:
            room, at, new = window, new, new + 1
        else:
            room, at = found
        out[k] = (at, window - room)
        if room > n:
            fit.put(room - n, at)
    return out


#: Splits text before the merges: the fixed pattern of the byte-level splitter that the vocabulary file names (``bpe.checked``).
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class WholeTextEncoder:
    """Ids of whole texts by a compiled public encoder, from the same vocabulary file. Special tokens are cut out first."""

    def __init__(self, path: str):
        import tiktoken

        a = bpe.automaton(path)
        ranks = {label: i for i, label in a.label.items() if label.decode("utf-8", "replace") not in a.special}
        self.special = a.special
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(a.special, key=len, reverse=True))) + ")") if a.special else None
        self.plain = tiktoken.Encoding("vocabulary", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary

    def encode(self, text: str | None) -> bytes:
        text = text or ""
        if self.cut is None or not any(s in text for s in self.special):
            ids = self.plain(text)
        else:
            ids = [i for p in self.cut.split(text) if p for i in ([self.special[p]] if p in self.special else self.plain(p))]
        return np.array(ids, "<u4").tobytes()


@lru_cache(2)
def _encoder(path: str) -> WholeTextEncoder:
    return WholeTextEncoder(path)


def _rows(columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in columns], [x.split()[0] for x in _SCHEMA.split(", ")])


def cut_batches(batches, path: str, window: int):
    """The pieces of each document: full windows, which are sequences, and a remainder without one."""
    from pyspark import TaskContext

    c = _encoder(path)
    base = TaskContext.get().partitionId() << LOCAL_BITS
    made = 0
    close = SEPARATOR.to_bytes(4, "little")
    for b in batches:
        rows = []
        for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text"), strict=True):
            ids = c.encode(text.as_py()) + close
            n = len(ids) // 4
            for start in range(0, n, window):
                piece = ids[4 * start : 4 * (start + window)]
                full = len(piece) == 4 * window
                rows.append((doc, start, len(piece) // 4, zlib.crc32(piece), n, base + made if full else None, 0 if full else None))
                made += full
        if rows:
            yield _rows(zip(*rows, strict=True))


def fit_batches(batches, window: int):
    """The remainders of one bin with their places."""
    from pyspark import TaskContext

    if not (batches := [b for b in batches if b.num_rows]):
        return
    base = (1 << BIN_BIT) + (TaskContext.get().partitionId() << LOCAL_BITS)
    rest = pa.Table.from_batches(batches).sort_by([(x, "ascending") for x in ("length", "doc_id", "start", "ids_crc32")])
    where = np.array(best_fit(rest.column("length").to_pylist(), window), np.int64)
    kept = [rest.column(x).combine_chunks() for x in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")]
    for at in range(0, len(where), 10_000):
        part = where[at : at + 10_000]
        yield _rows([*(x.slice(at, 10_000) for x in kept), base + part[:, 0], part[:, 1]])


def bins(remainders: int, tasks: int) -> int:
    """How many bins: as many as there are tasks at a time, but neither smaller than FEWEST nor larger than MOST."""
    return max(1, -(-remainders // MOST), min(tasks, remainders // FEWEST))


def packed(docs: DataFrame, path: str, window: int = WINDOW) -> DataFrame:
    """One row per piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``."""
    cut = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(on_worker(__name__, "cut_batches", path, window), _SCHEMA)
    pieces = written(cut, "pieces")
    rest = pieces.where(F.col("length") < window)
    n = bins(rest.count(), docs.sparkSession.sparkContext.defaultParallelism)
    return pieces.where(F.col("length") == window).unionAll(rest.repartition(n).mapInArrow(on_worker(__name__, "fit_batches", window), _SCHEMA))


def padding(pieces: DataFrame, window: int = WINDOW) -> DataFrame:
    """One row: sequences, tokens and the share of padding; a sequence whose length is a power of two isn't padded."""
    seq = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.bit_count("n") == 1, 0).otherwise(window - F.col("n"))
    return seq.agg(F.count(F.lit(1)).alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("padding")).withColumn("share", F.col("padding") / (F.col("tokens") + F.col("padding")))
