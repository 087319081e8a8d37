"""Bit codes: unary, Elias gamma and delta, and fixed-width low bits.

``pack_codes``, ``unpack_codes`` and the functions of sizes and low bits work on arrays; ``BitWriter`` and ``BitReader`` are their plain twins, bit by bit."""

from __future__ import annotations

import numpy as np


class BitWriter:
    def __init__(self):
        self.parts: list[str] = []

    def unary(self, n: int) -> None:
        """A zero and n ones: 011 is 2."""
        self.parts.append("0" + "1" * n)

    def fixed(self, x: int, width: int) -> None:
        if width:
            self.parts.append(format(x, f"0{width}b"))

    def gamma(self, x: int) -> None:
        b = format(x, "b")
        self.parts.append("0" * (len(b) - 1) + b)

    def delta(self, x: int) -> None:
        b = format(x, "b")
        self.gamma(len(b))
        self.parts.append(b[1:])

    def done(self) -> tuple[bytes, int]:
        bits = "".join(self.parts)
        padded = bits + "0" * (-len(bits) % 8)
        return (int(padded, 2).to_bytes(len(padded) // 8, "big") if padded else b""), len(bits)


class BitReader:
    def __init__(self, data: bytes):
        self.bits = "".join(format(b, "08b") for b in data)
        self.at = 0

    def unary(self) -> int:
        end = self.bits.find("0", self.at + 1)
        end = len(self.bits) if end < 0 else end
        n, self.at = end - self.at - 1, end
        return n

    def _zeros(self) -> int:
        one = self.bits.index("1", self.at)
        n, self.at = one - self.at, one + 1
        return n

    def fixed(self, width: int) -> int:
        if not width:
            return 0
        x = int(self.bits[self.at : self.at + width], 2)
        self.at += width
        return x

    def gamma(self) -> int:
        return self._rest(self._zeros())

    def delta(self) -> int:
        return self._rest(self.gamma() - 1)

    def _rest(self, width: int) -> int:
        return (1 << width) | self.fixed(width)


def encode_gaps(values: list[int], codec: str) -> bytes:
    """Ascending numbers from 0 as coded gaps; the first counts from -1, so every gap is 1 or more."""
    w = BitWriter()
    put = getattr(w, codec)
    last = -1
    for v in values:
        put(v - last)
        last = v
    return w.done()[0]


def decode_gaps(data: bytes, n: int, codec: str) -> list[int]:
    r = BitReader(data)
    get = getattr(r, codec)
    out, last = [], -1
    for _ in range(n):
        last += get()
        out.append(last)
    return out


def pack_low(values: np.ndarray, width: int) -> bytes:
    """The lowest ``width`` bits of each number, one after the other."""
    if not width or not len(values):
        return b""
    shifts = np.arange(width - 1, -1, -1, dtype=np.uint64)
    return np.packbits(((values.astype(np.uint64)[:, None] >> shifts) & np.uint64(1)).astype(np.uint8).ravel()).tobytes()


def unpack_low(data: bytes, n: int, width: int) -> np.ndarray:
    if not width or not n:
        return np.zeros(n, np.uint64)
    bits = np.unpackbits(np.frombuffer(data, np.uint8))[: n * width].reshape(n, width).astype(np.uint64)
    return (bits << np.arange(width - 1, -1, -1, dtype=np.uint64)).sum(1, dtype=np.uint64)


# ---- arrays of codes


def _log2(x: np.ndarray) -> np.ndarray:
    """Floor of log2 of integers from 1 on."""
    e = np.frexp(x.astype(np.float64))[1] - 1
    return e - ((np.uint64(1) << e.astype(np.uint64)) > x)  # the rounding of large numbers


def _emit(values: np.ndarray, widths: np.ndarray) -> bytes:
    """The lowest ``widths`` bits of each value, one after the other."""
    starts = np.cumsum(widths) - widths
    owner = np.repeat(np.arange(len(values)), widths)
    place = np.arange(len(owner)) - starts[owner]
    return np.packbits(((values[owner] >> (widths[owner] - 1 - place).astype(np.uint64)) & np.uint64(1)).astype(np.uint8)).tobytes()


def pack_codes(x: np.ndarray, codec: str) -> bytes:
    """Gamma or delta codes of integers from 1 on (below 2^40)."""
    x = np.asarray(x, np.uint64)
    if not len(x):
        return b""
    low = _log2(x)
    if codec == "gamma":
        return _emit(x, 2 * low + 1)
    head = low.astype(np.uint64) + np.uint64(1)
    shift = low.astype(np.uint64)
    return _emit((head << shift) | (x - (np.uint64(1) << shift)), 2 * _log2(head) + 1 + low)


def _windows(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """The bits, and for every bit the 56 bits from it on as the upper bits of a word."""
    raw = np.frombuffer(data + b"\0" * 16, np.uint8)
    n = 8 * len(data)
    word = np.zeros(len(data) + 1, np.uint64)
    for i in range(8):
        word = word << np.uint64(8) | raw[i : i + len(word)].astype(np.uint64)
    at = np.arange(n)
    return np.unpackbits(raw[: len(data)]), word[at >> 3] << (at & 7).astype(np.uint64)


def unpack_codes(data: bytes, n: int, codec: str) -> np.ndarray:
    """The first n numbers. The length of the code that would begin at a bit is known for all bits at once; codes are then found by
    following lengths."""
    if not n:
        return np.zeros(0, np.uint64)
    bits, word = _windows(data)
    at = np.arange(len(bits))
    one = np.minimum.accumulate(np.where(bits == 1, at, len(bits) - 1)[::-1])[::-1]
    zeros = one - at
    head = word[one] >> (np.uint64(63) - np.minimum(zeros, 55).astype(np.uint64))
    tail = np.zeros(len(bits), np.int64) if codec == "gamma" else np.minimum(head, np.uint64(60)).astype(np.int64) - 1
    step = (at + 2 * zeros + 1 + tail).tolist()
    starts, p = [], 0
    for _ in range(n):
        starts.append(p)
        p = step[p] if p < len(step) else p
    starts = np.array(starts)
    if codec == "gamma":
        return head[starts]
    low = tail[starts]
    rest = word[np.minimum(starts + 2 * zeros[starts] + 1, len(bits) - 1)]
    return (np.uint64(1) << low.astype(np.uint64)) | np.where(low > 0, rest >> (64 - np.maximum(low, 1)).astype(np.uint64), np.uint64(0))


def pack_sizes(sizes: np.ndarray) -> bytes:
    """Unary: for each size a zero and as many ones."""
    sizes = np.asarray(sizes, np.int64)
    bits = np.ones(int(sizes.sum()) + len(sizes), np.uint8)
    bits[np.cumsum(sizes + 1) - (sizes + 1)] = 0
    return np.packbits(bits).tobytes()


def unpack_sizes(data: bytes) -> np.ndarray:
    """All sizes; padding adds empty ones at the end."""
    zeros = np.flatnonzero(np.r_[np.unpackbits(np.frombuffer(data, np.uint8)), 0] == 0)
    return np.diff(zeros) - 1


def gaps_of(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Gaps of ascending numbers within runs of ``counts``; each run begins at -1."""
    values = np.asarray(values, np.int64)
    before = np.r_[-1, values[:-1]]
    before[np.cumsum(counts) - counts] = -1
    return values - before


def from_gaps(gaps: np.ndarray, counts: np.ndarray) -> np.ndarray:
    total = np.cumsum(gaps.astype(np.int64))
    first = np.cumsum(counts) - counts
    base = np.where(first > 0, total[np.maximum(first - 1, 0)], 0)
    return total - np.repeat(base, counts) - 1
