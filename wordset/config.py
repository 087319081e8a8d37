"""Settings of an index; two indexes can be intersected only if theirs are equal."""

from __future__ import annotations

import random
from dataclasses import dataclass, replace
from functools import cached_property

#: Word widths: even powers of two, so that the group size is one as well.
WIDTHS = (4, 16, 64, 256, 1024, 4096)


@dataclass(frozen=True)
class Cfg:
    """w: bits of a word image. m: images per group. universe_bits: elements are below 2^universe_bits.

    g orders the elements (``mulshift``: a bijection in portable integer arithmetic, up to 32 bits; ``xx64``: Spark's xxhash64,
    64 bits, any long). h draws image bits (``cw31``: linear modulo a prime; ``xx64``; ``perm``: the first bits of
    another permutation; ``sql:`` and an expression over ``{x}``: a hash of one's own). bucket: mean size of a bucket of the lookup baseline."""

    w: int = 64
    m: int = 4
    universe_bits: int = 32
    g: str = "mulshift"
    h: str = "cw31"
    seed: int = 42
    bucket: int = 32

    def __post_init__(self):
        if self.w not in WIDTHS:
            raise ValueError(f"w must be one of {WIDTHS}")
        if self.m < 1:
            raise ValueError("m must be 1 or more")
        if self.g not in ("mulshift", "xx64", "hash") or self.h not in ("cw31", "xx64", "perm") and not self.h.startswith("sql:"):
            raise ValueError("unknown g or h")
        if self.g == "mulshift" and not (2 <= self.universe_bits <= 32 and self.universe_bits % 2 == 0):
            raise ValueError("mulshift needs an even universe_bits of 2 to 32")
        if self.g != "mulshift" and self.universe_bits != 64:
            object.__setattr__(self, "universe_bits", 64)

    @property
    def root(self) -> int:
        """The target size of a group, the square root of w."""
        return 1 << (self.w.bit_length() - 1) // 2

    @property
    def words(self) -> int:
        """Longs per image."""
        return max(1, self.w // 64)

    def images(self, m: int | None = None) -> list[list[str]]:
        """Column names of the first m images, each a list of its words."""
        m = self.m if m is None else m
        return [[f"img_{j}"] if self.words == 1 else [f"img_{j}_{k}" for k in range(self.words)] for j in range(1, m + 1)]

    @cached_property
    def rounds(self) -> list[tuple[int, int]]:
        """Multiplier and addend of the two rounds of the permutation."""
        r = random.Random(f"g{self.seed}")
        return [(r.randrange(1 << (min(self.universe_bits, 31) - 1), 1 << min(self.universe_bits, 31)) | 1, r.randrange(1 << self.universe_bits)) for _ in range(2)]

    def line(self, j: int) -> tuple[int, int]:
        """Slope and intercept of hash function j, apart from those of g."""
        r = random.Random(f"h{self.seed}/{j}")
        return r.randrange(1, (1 << 31) - 1), r.randrange((1 << 31) - 1)

    def with_(self, **change) -> Cfg:
        return replace(self, **change)
