"""Byte-pair encoding by a tokenization automaton.

The automaton reads tokens. It starts with one state that every byte leads back to; each merge (u, v) -> w, in
order, applies one gadget: the state behind u is split off and loses its arc v, every state that may go u and
then v gets an arc w, and the state behind w starts as a copy of the one behind v. A token sequence is a path
of the finished automaton exactly if it is what the merges make of its bytes.

Since all arcs of a token lead to one state, a state is named by the token before it, and a row of the transition table says which
tokens may come next. Nearly all may (97 % of 2.5 billion arcs of a vocabulary of 50,000), so a row holds what differs from a row of open arcs.
A gadget cuts one arc of one state; later states copy the row, and later tokens that begin with the cut one have no arc either. Tokens are therefore
numbered by a walk over the forest of first parts, youngest first, in which all that a cut closes is one run of numbers. A compiled row is
a sorted list of such runs, and a transition is one binary search in it. A word is encoded by walking the automaton: from each place along the longest
token whose arc is open, and back from places that prove dead, of which each is met once. Decoding emits the labels of the arcs.

Texts are first split into words by the vocabulary's own pattern; special tokens of the vocabulary file are cut
out before that, as the public library does. Words are encoded once per worker and kept in a table of bounded size.

Edge cases: null and empty texts have no tokens; bytes of any text are in the vocabulary, so nothing is unknown;
very long words cost linear time in their length; an empty table gives an empty result, repeated rows are answered each, and other columns play no
part, whatever their names.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata
from array import array
from bisect import bisect_right
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordset.functions.worker import on_worker

#: Words kept per worker, and the longest word that is kept (bytes).
KEPT_WORDS = 600_000
KEPT_LENGTH = 64


def _byte_letters() -> dict[str, int]:
    """The letters that the vocabulary file writes for bytes: printable Latin-1 bytes stand for themselves, the
    others for the letters from U+0100 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


def checked(file: dict) -> None:
    """Refuses a vocabulary file whose texts are normalised or split in another way than here."""
    split = file.get("pre_tokenizer") or {}
    model = file["model"]
    odd = [k for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges") if model.get(k)]
    if split.get("type") != "ByteLevel" or split.get("add_prefix_space") or not split.get("use_regex", True) or file.get("normalizer") or odd:
        raise ValueError(f"only byte-level vocabularies with the usual split are supported, not {split}, {file.get('normalizer')}, {odd}")


class Automaton:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            file = json.load(f)
        checked(file)
        letters = _byte_letters()
        vocab = file["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in file["added_tokens"]}
        self.label: dict[int, bytes] = {i: bytes(map(letters.__getitem__, t)) for t, i in vocab.items() if t not in self.special}
        self.label |= {i: t.encode() for t, i in self.special.items()}
        self.left: dict[int, int] = {}
        self.right: dict[int, int] = {}
        self.born: dict[int, int] = {i: -1 for i, t in self.label.items() if len(t) == 1}
        self.merge: dict[tuple[int, int], int] = {}
        self.token: dict[bytes, int] = {t: i for i, t in self.label.items() if i in self.born}
        self.longest = 1
        rows: dict[int, list[int]] = {i: [] for i in self.born}  # state -> gadgets whose cuts its row has
        for k, m in enumerate(file["model"]["merges"]):
            u, v = m if isinstance(m, list) else m.split(" ")
            self._gadget(vocab[u], vocab[v], vocab[u + v], k, rows)
        self.size = {t: len(x) for x, t in self.token.items()}
        self.shorter = {t: next((self.token[x[:k]] for k in range(len(x) - 1, 0, -1) if x[:k] in self.token), -1) for x, t in self.token.items()}
        self._compile(rows)

    def _gadget(self, u: int, v: int, w: int, k: int, rows: dict[int, list[int]]) -> None:
        if self.merge.setdefault((u, v), k) == k:
            rows[u].append(k)  # the state behind u loses its arc v
        if w in self.born:
            return  # the same token by a later merge; its pair can't stand any more
        rows[w] = rows[v][:-1] if u == v else rows[v][:]  # the state behind w is the one behind v as it was
        self.left[w], self.right[w], self.born[w] = u, v, k
        # no path ever holds u v if the arc was cut before, and then w has no arc either
        if self.token.get(self.label[u]) == u and self.token.get(self.label[v]) == v and self._open(u, v, k):
            self.token[self.label[w]] = w
            self.longest = max(self.longest, len(self.label[w]))

    def _compile(self, rows: dict[int, list[int]]) -> None:
        """The rows of all states as sorted runs of closed numbers, end to end."""
        kids: dict[int, list[int]] = {}
        for t in sorted(self.left, key=self.born.__getitem__, reverse=True):
            kids.setdefault(self.left[t], []).append(t)
        self.number: dict[int, int] = {}
        end: dict[int, int] = {}  # the number after the last below a token
        walk = [t for t, k in self.born.items() if k < 0][::-1]
        done: list[int] = []
        while walk:
            t = walk.pop()
            self.number[t] = len(self.number)
            done.append(t)
            walk += kids.get(t, [])[::-1]
        for t in reversed(done):
            end[t] = max([self.number[t] + 1, *(end[c] for c in kids.get(t, [])[-1:])])
        # the cut of gadget k at v closes v and the tokens on v that are no older
        lo, hi = np.zeros(len(self.merge) + 1, np.int64), np.zeros(len(self.merge) + 1, np.int64)
        place = {k: i for i, k in enumerate(self.merge.values())}
        for (_, v), k in self.merge.items():
            own = kids.get(v, [])
            young = bisect_right(own, -k, key=lambda c: -self.born[c])
            lo[place[k]] = self.number[v]
            hi[place[k]] = end[own[young - 1]] - 1 if young else self.number[v]
        states = list(rows)
        self.width = len(self.number)
        counts = np.fromiter(map(len, rows.values()), np.int64, len(rows))
        cuts = np.fromiter((place[k] for r in rows.values() for k in r), np.int64, int(counts.sum()))
        base = np.repeat(np.arange(len(states)) * self.width, counts)
        first, last = base + lo[cuts], base + hi[cuts]
        order = np.lexsort((-last, first))
        first, last = first[order], last[order]
        apart = np.r_[True, first[1:] > np.maximum.accumulate(last)[:-1]] if len(first) else np.zeros(0, bool)  # runs lie in each other or apart
        first, last = first[apart], last[apart]
        bounds = np.searchsorted(first, np.arange(len(states) + 1) * self.width).tolist()
        self.row = {t: (i * self.width, bounds[i], bounds[i + 1]) for i, t in enumerate(states)}
        self.first, self.last = array("q", first.tobytes()), array("q", last.tobytes())

    def table(self) -> dict[str, int]:
        """States, runs and bytes of the compiled rows, and the arcs that they stand for."""
        closed = sum(b - a + 1 for a, b in zip(self.first, self.last, strict=True))
        return {"states": len(self.row), "runs": len(self.first), "bytes": 16 * len(self.first), "open_arcs": len(self.row) * self.width - closed, "closed_arcs": closed}

    def _open(self, x: int, y: int, k: int) -> bool:
        """Whether the state behind x has the arc y after the merges before k."""
        born, left, right, merge = self.born, self.left, self.right, self.merge
        while True:
            if merge.get((x, y), k) < k:
                return False
            bx, by = born[x], born[y]
            if bx < 0 and by < 0:
                return True
            if bx > by:  # the state behind x began as a copy of the one behind its right part
                x, k = right[x], bx
            else:  # y goes where its left part went once its own gadget had cut its arc
                y, k = left[y], by + 1

    def may_follow(self, x: int, y: int) -> bool:
        """Whether the state behind x has the arc y, by the table."""
        base, start, stop = self.row[x]
        at = base + self.number[y]
        i = bisect_right(self.first, at, start, stop)
        return i == start or self.last[i - 1] < at

    def encode_word(self, word: bytes) -> list[int]:
        if (one := self.token.get(word)) is not None:
            return [one]
        token, follow, size, shorter = self.token, self.may_follow, self.size, self.shorter
        n, pos = len(word), 0
        out: list[int] = []
        dead: set[int] = set()  # places from which no path leads to the end

        def longest(at: int) -> int:
            for end in range(min(n, at + self.longest), at, -1):
                if (t := token.get(word[at:end])) is not None:
                    return t
            raise ValueError("a byte without a token")

        t = longest(0)
        while True:
            end = pos + size[t]
            if end not in dead and (not out or follow(out[-1], t)):
                out.append(t)
                if end == n:
                    return out
                pos = end
                t = longest(pos)
                continue
            t = shorter[t]
            while t < 0:  # nothing fits here
                dead.add(pos)
                t = out.pop()
                pos -= size[t]
                t = shorter[t]


# ---- splitting

_SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
_TAIL = r"'s|'t|'re|'ve|'m|'ll|'d| ?{L}+| ?{N}+| ?{O}+|[{S}]+(?![^{S}])|[{S}]+"
_OTHER_DIGITS = "".join(c for c in map(chr, range(256)) if unicodedata.category(c) in ("No", "Nl"))
#: For texts of Latin-1 letters only: sets of 256 characters, which the standard library tests by one look-up.
_NARROW = re.compile(_TAIL.format(L=rf"[^\W\d_{_OTHER_DIGITS}]", N=rf"[\d{_OTHER_DIGITS}]", O=rf"(?:[^{_SPACE}\w]|_)", S=_SPACE))
_WIDE = regex.compile(_TAIL.format(L=r"\p{L}", N=r"\p{N}", O=rf"[^{_SPACE}\p{{L}}\p{{N}}]", S=_SPACE))


def split_words(text: str) -> list[str]:
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return _WIDE.findall(text)
    return _NARROW.findall(text)


class _Words(dict):
    """Word -> its ids as little-endian unsigned 32-bit integers."""

    def __init__(self, encode):
        self.encode = encode

    def __missing__(self, word: str) -> bytes:
        ids = np.array(self.encode(word.encode()), "<u4").tobytes()
        if len(word) <= KEPT_LENGTH:
            if len(self) >= KEPT_WORDS:
                self.clear()
            self[word] = ids
        return ids


class Codec:
    def __init__(self, automaton: Automaton, encode=None):
        self.automaton = automaton
        self.words = _Words(encode or automaton.encode_word)
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(automaton.special, key=len, reverse=True))) + ")") if automaton.special else None
        self.labels = [automaton.label.get(i, b"") for i in range(max(automaton.label) + 1)]

    def encode(self, text: str | None) -> bytes:
        text = text or ""
        get, special = self.words.__getitem__, self.automaton.special
        if self.cut is None or not any(s in text for s in special):
            return b"".join(map(get, split_words(text)))
        return b"".join(np.array([special[p]], "<u4").tobytes() if p in special else b"".join(map(get, split_words(p))) for p in self.cut.split(text) if p)

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.labels.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@lru_cache(2)
def automaton(path: str) -> Automaton:
    return Automaton(path)


@lru_cache(2)
def codec(path: str) -> Codec:
    return Codec(automaton(path))


def encode_batches(batches, path: str):
    c = codec(path)
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([c.encode(t.as_py()) for t in b.column("text")], pa.binary())], ["doc_id", "ids"])


def decode_batches(batches, path: str):
    c = codec(path)
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([None if x.as_py() is None else c.decode(x.as_py()).decode("utf-8", "replace") for x in b.column("ids")], pa.string())], ["doc_id", "text"])


def digest_batches(batches, path: str):
    c = codec(path)
    for b in batches:
        n, ids_sha, text_sha = [], [], []
        for t in b.column("text"):
            ids = c.encode(t.as_py())
            n.append(len(ids) // 4)
            ids_sha.append(hashlib.sha256(ids).hexdigest())
            text_sha.append(hashlib.sha256(c.decode(ids).decode("utf-8", "replace").encode()).hexdigest())
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids_sha), pa.array(text_sha)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def _input(docs: DataFrame, column: str) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), column)


def encoded(docs: DataFrame, path: str) -> DataFrame:
    """``doc_id, ids``: the token ids of every whole text, as little-endian unsigned 32-bit integers."""
    return _input(docs, "text").mapInArrow(on_worker(__name__, "encode_batches", path), "doc_id long, ids binary")


def decoded(tokens: DataFrame, path: str) -> DataFrame:
    """``doc_id, text`` of ``doc_id, ids``; ids that make no valid UTF-8 decode to replacement characters."""
    return _input(tokens, "ids").mapInArrow(on_worker(__name__, "decode_batches", path), "doc_id long, text string")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` of every whole text, encoded and decoded again."""
    return _input(docs, "text").mapInArrow(on_worker(__name__, "digest_batches", path), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
