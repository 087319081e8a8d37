"""Cursor programs over the blocks of a query, each with a count of what it did: ``comparisons`` are counted, not estimated.

A block holds the members of one set below a prefix as ascending unsigned numbers (their places in the common order). Every
program returns the common numbers, ascending, and its counters. Smaller sets come first.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np

from wordset.config import Cfg
from wordset.functions import hashing


@dataclass
class Block:
    t: int
    zs: np.ndarray
    ns: np.ndarray
    imgs: np.ndarray
    g: np.ndarray

    def __post_init__(self):
        self.low, self.high = (int(self.zs[0]), int(self.zs[-1])) if len(self.zs) else (0, -1)

    def _placed(self, values: np.ndarray) -> np.ndarray:
        """Values of the groups at the places of their prefixes, zero where there is no group."""
        if self.high - self.low + 1 == len(self.zs):
            return np.ascontiguousarray(values)
        out = np.zeros(self.high - self.low + 1, values.dtype)
        out[(self.zs - np.uint64(self.low)).astype(np.int64)] = values
        return out

    @cached_property
    def size(self) -> np.ndarray:
        return self._placed(self.ns)

    @cached_property
    def start(self) -> np.ndarray:
        return np.cumsum(self.size) - self.size

    @cached_property
    def values(self) -> list[int]:
        return self.g.tolist()

    @cached_property
    def table(self) -> set[int]:
        return set(self.values)

    @cached_property
    def lanes(self) -> SkipList:
        return SkipList(self.values)

    def members(self, groups: np.ndarray) -> np.ndarray:
        """Members of some groups in order: by their places if few, by a mask over all members if many."""
        if len(groups) * 3 < len(self.size):
            row, place = _spread(self.size[groups])
            return self.g[self.start[groups][row] + place]
        if len(groups) * 10 > len(self.size) * 9:
            return self.g  # nearly all: leaving few out costs more than it saves
        mask = np.zeros(len(self.size), bool)
        mask[groups] = True
        return self.g[np.repeat(mask, self.size)]

    def image(self, j: int) -> np.ndarray:
        if not hasattr(self, "_images"):
            self._images = {}
        if j not in self._images:
            self._images[j] = self._placed(self.imgs[:, j])
        return self._images[j]


def _array(values) -> np.ndarray:
    return np.array(values, np.uint64)


def merge(blocks: list[Block], cfg: Cfg):
    """Lists in step, pair by pair. Two cursors compare once for every member they pass until a list ends, and once for both of equal ones."""
    now, count, fetched = blocks[0].g, 0, sum(len(b.g) for b in blocks)
    for b in blocks[1:]:
        if len(now) and len(b.g):
            end = min(now[-1], b.g[-1])
            passed = np.searchsorted(now, end, "right") + np.searchsorted(b.g, end, "right")
            now = np.intersect1d(now, b.g, assume_unique=True)
            count += int(passed) - len(now)
        else:
            now = now[:0]
    return now, {"comparisons": count, "elems_fetched": fetched}


def hash_probe(blocks: list[Block], cfg: Cfg):
    """Members of the smallest list in a hash table of each other list, up to the first miss."""
    tables = [b.table for b in blocks[1:]]
    out, probes = [], 0
    for x in blocks[0].values:
        for t in tables:
            probes += 1
            if x not in t:
                break
        else:
            out.append(x)
    return _array(out), {"comparisons": probes}


class SkipList:
    """Express lanes over a sorted list: lane i holds every fourth member of lane i-1."""

    STEP = 4

    def __init__(self, values: list[int]):
        self.lanes = [values]
        while len(self.lanes[-1]) > self.STEP:
            self.lanes.append(self.lanes[-1][:: self.STEP])

    def find(self, x: int, count: list[int]) -> bool:
        at = 0
        for lane in reversed(self.lanes):
            while at + 1 < len(lane) and lane[at + 1] <= x:
                at += 1
                count[0] += 1
            count[0] += 1
            if lane is not self.lanes[0]:
                at *= self.STEP
        return bool(self.lanes[0]) and self.lanes[0][at] == x


def skip_list(blocks: list[Block], cfg: Cfg):
    lists, count, out = [b.lanes for b in blocks[1:]], [0], []
    for x in blocks[0].values:
        if all(s.find(x, count) for s in lists):
            out.append(x)
    return _array(out), {"comparisons": count[0]}


_ONES = np.uint64(0x0101010101010101)
_HIGH = np.uint64(0x8080808080808080)


def packed_codes(blocks: list[Block], cfg: Cfg):
    """Codes of eight bits, packed eight to a word by bucket: a candidate is compared with a word of codes at once, and members behind equal
    codes are verified. Counted are words compared and members verified."""
    now, count = blocks[0].g, 0
    for b in blocks[1:]:
        n = max(1, len(b.g) // 8)
        varied = (int(b.g[0]) ^ int(b.g[-1])).bit_length() if len(b.g) else 0  # members of a cut set share the bits before
        shift = np.uint64(max(0, varied - hashing.bit_length(n) - 8))
        byte, eight = np.uint64(255), np.uint64(8)
        bucket = b.g >> shift >> eight
        first = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]) if len(bucket) else np.zeros(0, np.int64)
        size = np.diff(np.r_[first, len(bucket)])
        words = -(-size // 8)
        start = np.cumsum(words) - words
        row, place = _spread(size)
        packed = np.zeros(8 * int(words.sum()), np.uint8)
        packed[8 * start[row] + place] = ((b.g >> shift) & byte).astype(np.uint8)
        packed = packed.view("<u8")
        # the bucket of each candidate, and the words in it
        at = np.searchsorted(bucket[first], now >> shift >> eight)
        inside = np.flatnonzero(at < len(first))
        inside = inside[bucket[first][at[inside]] == (now >> shift >> eight)[inside]]
        owner, word = _spread(words[at[inside]])
        owner = inside[owner]
        word += start[at[owner]]
        v = packed[word] ^ (((now[owner] >> shift) & byte) * _ONES)
        hit = (v - _ONES) & ~v & _HIGH  # the high bit of each byte that is zero, and maybe of the one after it
        count += len(v)
        some = np.flatnonzero(hit)
        bits = np.unpackbits(hit[some].astype("<u8").view(np.uint8).reshape(-1, 8) >> 7, axis=1)[:, 7::8]
        which, lane = np.nonzero(bits)
        owner, word = owner[some][which], word[some][which]
        place = 8 * (word - start[at[owner]]) + lane
        real = place < size[at[owner]]
        owner, place = owner[real], place[real]
        count += len(owner)
        same = b.g[first[at[owner]] + place] == now[owner]
        now = now[owner[same]]
    return now, {"comparisons": int(count)}


def lookup(blocks: list[Block], cfg: Cfg):
    """A directory of equal ranges of about ``cfg.bucket`` members; each candidate scans one bucket."""
    now, count = blocks[0].g, 0
    for b in blocks[1:]:
        if not len(b.g):
            return _array([]), {"comparisons": count}
        low, span = b.g[0], int(b.g[-1]) - int(b.g[0]) + 1
        width = np.uint64(max(1, span * cfg.bucket // len(b.g)))
        slot = ((b.g - low) // width).astype(np.int64)
        starts = np.searchsorted(slot, np.arange(int(slot[-1]) + 2))
        now = now[(now >= low) & (now <= b.g[-1])]
        i = ((now - low) // width).astype(np.int64)
        owner, place = _spread(starts[i + 1] - starts[i])
        count += len(owner)
        now = now[owner[b.g[starts[i][owner] + place] == now[owner]]]
    return now, {"comparisons": count}


def _gallop(a: list[int], x: int, lo: int, count: list[int]) -> int:
    """The first place from lo on whose member is x or more: doubling steps, then halving."""
    step, hi = 1, lo
    while hi < len(a) and a[hi] < x:
        count[0] += 1
        lo, hi, step = hi + 1, hi + step, step * 2
    count[0] += hi < len(a)
    return _search(a, x, lo, min(hi, len(a)), count)


def _search(a: list[int], x: int, lo: int, hi: int, count: list[int]) -> int:
    """``bisect_left`` that counts its comparisons."""
    while lo < hi:
        mid = (lo + hi) // 2
        count[0] += 1
        if a[mid] < x:
            lo = mid + 1
        else:
            hi = mid
    return lo


def smallest_first(blocks: list[Block], cfg: Cfg):
    """Candidates of the smallest list, narrowed list by list with galloping cursors."""
    now, count = blocks[0].values, [0]
    for b in blocks[1:]:
        a, at, keep = b.values, 0, []
        for x in now:
            at = _gallop(a, x, at, count)
            if at == len(a):
                break
            if a[at] == x:
                keep.append(x)
        now = keep
    return _array(now), {"comparisons": count[0]}


def round_robin(blocks: list[Block], cfg: Cfg):
    """One candidate is galloped for in list after list; a miss makes the successor found the next candidate."""
    lists, count, out = [b.values for b in blocks], [0], []
    k, at = len(lists), [0] * len(lists)
    if not all(lists):
        return _array([]), {"comparisons": 0}
    x, agreed, i = lists[0][0], 1, 1 % k
    while True:
        if agreed == k:
            out.append(x)
            at[i] = _gallop(lists[i], x + 1, at[i], count)
            if at[i] == len(lists[i]):
                break
            x, agreed, i = lists[i][at[i]], 1, (i + 1) % k
            continue
        at[i] = _gallop(lists[i], x, at[i], count)
        if at[i] == len(lists[i]):
            break
        if lists[i][at[i]] == x:
            agreed += 1
        else:
            x, agreed = lists[i][at[i]], 1
        i = (i + 1) % k
    return _array(out), {"comparisons": count[0]}


def median_split(blocks: list[Block], cfg: Cfg):
    """The median of the smaller list is searched in the larger, and both halves are solved; k lists pair by pair."""
    count = [0]

    def pair(a: list[int], b: list[int]) -> list[int]:
        out, stack = [], [(0, len(a), 0, len(b))]
        while stack:
            a0, a1, b0, b1 = stack.pop()
            if a0 >= a1 or b0 >= b1:
                continue
            if a1 - a0 <= b1 - b0:
                m = (a0 + a1) // 2
                p = _search(b, a[m], b0, b1, count)
                hit = p < b1 and b[p] == a[m]
                stack += [(m + 1, a1, p + hit, b1), (a0, m, b0, p)]
                value = a[m]
            else:
                m = (b0 + b1) // 2
                p = _search(a, b[m], a0, a1, count)
                hit = p < a1 and a[p] == b[m]
                stack += [(p + hit, a1, m + 1, b1), (a0, p, b0, m)]
                value = b[m]
            count[0] += 1  # whether it is there
            if hit:
                out.append(value)
        return sorted(out)

    now = blocks[0].values
    for b in blocks[1:]:
        now = pair(now, b.values)
    return _array(now), {"comparisons": count[0]}


def hybrid_adaptive(blocks: list[Block], cfg: Cfg):
    """Candidates always come from the list with fewest members left, and go to the next longer one first."""
    lists, count, out = [b.values for b in blocks], [0], []
    at = [0] * len(lists)
    while True:
        order = sorted(range(len(lists)), key=lambda i: len(lists[i]) - at[i])
        first = order[0]
        if at[first] >= len(lists[first]):
            break
        x = lists[first][at[first]]
        at[first] += 1
        for i in order[1:]:
            at[i] = _gallop(lists[i], x, at[i], count)
            if at[i] == len(lists[i]):
                return _array(out), {"comparisons": count[0]}
            if lists[i][at[i]] != x:
                # the successor is the least that can be common; the first list goes on from there
                at[first] = _gallop(lists[first], lists[i][at[i]], at[first], count)
                break
        else:
            out.append(x)
    return _array(out), {"comparisons": count[0]}


def binary_probe(blocks: list[Block], cfg: Cfg):
    """Members of the smallest list by binary search within the facing group of each larger one, whose bounds are a directory."""
    now, count = blocks[0].g, 0
    t = hashing.t_probe(max(1, len(blocks[0].g)))
    for b in blocks[1:]:
        shift = np.uint64(cfg.universe_bits - min(t + blocks[0].t, cfg.universe_bits))
        z = b.g >> shift
        first = np.flatnonzero(np.r_[True, z[1:] != z[:-1]]) if len(z) else np.zeros(0, np.int64)
        ends = np.r_[first, len(z)]
        at = np.searchsorted(z[first], now >> shift)  # the group's place; empty ones have none
        here = at < len(first)
        here[here] = z[first][at[here]] == (now >> shift)[here]
        now, at = now[here], at[here]
        lo, hi = ends[at], ends[at + 1]
        end = hi.copy()
        open_ = np.flatnonzero(lo < hi)
        while len(open_):
            mid = (lo[open_] + hi[open_]) // 2
            count += len(open_)
            less = b.g[mid] < now[open_]
            lo[open_[less]] = mid[less] + 1
            hi[open_[~less]] = mid[~less]
            open_ = open_[lo[open_] < hi[open_]]
        found = lo < end
        found[found] = b.g[lo[found]] == now[found]
        now = now[found]
    return now, {"comparisons": int(count)}


def image_scan(blocks: list[Block], cfg: Cfg):
    """Groups aligned by prefix, tested image by image, and only the survivors' members merged.

    Groups lie at the place of their prefix, empty ones with image zero, so sets of one prefix length align without any
    search, and images of a shorter prefix are repeated for the prefixes below it."""
    last = blocks[-1]
    if any(not len(b.zs) for b in blocks):
        return _array([]), {}
    # the finest prefixes that all sets cover
    low = max(b.low << (last.t - b.t) for b in blocks)
    high = min(((b.high + 1) << (last.t - b.t)) - 1 for b in blocks)
    if low > high:
        return _array([]), {}

    def column(b: Block, values: np.ndarray) -> np.ndarray:
        d = last.t - b.t
        part = values[(low >> d) - b.low : (high >> d) - b.low + 1]
        if not d:
            return part
        return np.repeat(part, 1 << d)[low - (low >> d << d) :][: high - low + 1]

    met = np.logical_and.reduce([column(b, b.size) > 0 for b in blocks])
    alive = None
    for j in range(last.imgs.shape[1]):
        if alive is None:
            both = column(blocks[0], blocks[0].image(j))
            for b in blocks[1:]:
                both = both & column(b, b.image(j))
            alive = np.flatnonzero(both) + low
        else:  # a later image only where the ones before met
            both = np.bitwise_and.reduce([b.image(j)[(alive >> (last.t - b.t)) - b.low] for b in blocks])
            alive = alive[both != 0]
    now, fetched = None, 0
    for b in sorted(blocks, key=lambda b: b.t, reverse=True):
        groups = alive >> (last.t - b.t)
        if b.t != last.t:
            groups = np.unique(groups)
        groups = groups - b.low
        part = b.members(groups)
        fetched += len(part)
        now = part if now is None else np.intersect1d(now, part, assume_unique=True)
    z = now >> np.uint64(cfg.universe_bits - last.t)  # ascending
    hit = int(np.count_nonzero(z[1:] != z[:-1])) + bool(len(z))
    return now, {"pairs_met": int(met.sum()), "pairs_passed": len(alive), "pairs_hit": hit, "elems_fetched": fetched}


def _spread(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For counts 2, 3: owners 0 0 1 1 1 and places 0 1 0 1 2."""
    owner = np.repeat(np.arange(len(counts)), counts)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)


METHODS = {
    "merge": merge,
    "hash": hash_probe,
    "skip": skip_list,
    "packed": packed_codes,
    "lookup": lookup,
    "svs": smallest_first,
    "adaptive": round_robin,
    "median": median_split,
    "hybrid": hybrid_adaptive,
    "probe": binary_probe,
    "scan": image_scan,
}
