"""Permutation, hash functions and group counts as SQL text for Spark, and for DuckDB in the oracles.

All arithmetic stays below 2^63: Spark raises on overflow.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions.worker import column_kernel

PRIME = (1 << 31) - 1


def xor(a: str, b: str, duck: bool = False) -> str:
    return f"xor({a}, {b})" if duck else f"({a} ^ {b})"


def shr(a: str, n: str | int, duck: bool = False) -> str:
    return f"({a} >> {n})" if duck else f"shiftrightunsigned({a}, {n})"


def div(a: str, b: str | int, duck: bool = False) -> str:
    return f"({a} // {b})" if duck else f"({a} div {b})"


def g_sql(x: str, cfg: Cfg, duck: bool = False) -> str:
    """The place of x in the common random order."""
    if cfg.g != "mulshift":
        return f"xxhash64({cfg.seed}, {x})"
    mask = (1 << cfg.universe_bits) - 1
    for a, b in cfg.rounds:
        x = f"(({xor(x, shr(x, cfg.universe_bits // 2, duck), duck)} * {a} + {b}) & {mask})"
    return x


def h_sql(x: str, j: int, cfg: Cfg, duck: bool = False) -> str:
    """The image bit of x under hash function j: 0 to w-1."""
    if cfg.h.startswith("sql:"):
        return f"({cfg.h[4:].format(x=x)})"
    if cfg.h == "xx64":
        return f"(xxhash64({cfg.seed + 7919 * j}, 'bit', {x}) & {cfg.w - 1})"
    if cfg.h == "perm":
        return f"shiftrightunsigned(xxhash64({cfg.seed + 104729 * j}, {x}), {64 - (cfg.w.bit_length() - 1)})"
    a, b = cfg.line(j)
    wide = f"({x} % {PRIME})" if cfg.universe_bits > 30 else x
    return f"((({wide} * {a} + {b}) % {PRIME}) % {cfg.w})"


def prefix_sql(g: str, t: str | int, cfg: Cfg, duck: bool = False) -> str:
    """The leading t bits of g; a shift by the whole width is no shift in Java, so t = 0 is apart."""
    if isinstance(t, int):
        return shr(g, cfg.universe_bits - t, duck) if t else f"({g} * 0)"
    return f"(case when {t} = 0 then 0 else {shr(g, f'({cfg.universe_bits} - {t})', duck)} end)"


def bits_of_sql(c: str) -> str:
    """Ceiling of log2 of c, an integer: 0 for 1 and below."""
    return f"(case when {c} <= 1 then 0 else length(bin({c} - 1)) end)"


def t_scan_sql(n: str, cfg: Cfg, duck: bool = False) -> str:
    """Bits so that groups of a set of n have about root(w) members."""
    return bits_of_sql(div(f"({n} + {cfg.root - 1})", cfg.root, duck))


def g(x: str, cfg: Cfg) -> Column:
    return F.expr(g_sql(x, cfg))


def h(x: str, j: int, cfg: Cfg) -> Column:
    return F.expr(h_sql(x, j, cfg)).cast("int")


def bit_length(n: int) -> int:
    return max(0, (n - 1).bit_length())


def t_scan(n: int, cfg: Cfg) -> int:
    return bit_length(-(-n // cfg.root))


def t_pair(n1: int, n2: int, w: int) -> int:
    """The least t with 4^t w >= n1 n2: as many groups in both sets."""
    return (bit_length(-(-n1 * n2 // w)) + 1) // 2


def t_probe(n1: int) -> int:
    """About one member of the smaller set per group."""
    return bit_length(n1)


def fixed_sizes(n1: int, n2: int, w: int) -> tuple[int, int]:
    """Group sizes of a pair as powers of two, s* <= s <= 2 s* for the sizes s* that make the fewest pairs."""

    def power(num: int, den: int, n: int) -> int:
        s = 1
        while s * s * den < w * num:  # s < sqrt(w num / den)
            s *= 2
        return max(1, min(s, 1 << bit_length(n)))

    return power(n1, n2, n1), power(n2, n1, n2)


def h_array(x: np.ndarray, j: int, cfg: Cfg) -> np.ndarray:
    """``h_sql`` of elements below 2^32 under ``cw31``."""
    a, b = cfg.line(j)
    return (x.astype(np.int64) % PRIME * a + b) % PRIME % cfg.w


# ---- the inverse of g


def g_inverse_array(values: pa.Array, cfg: Cfg) -> pa.Array:
    x = values.to_numpy(zero_copy_only=False).astype(np.uint64)
    mask = np.uint64((1 << cfg.universe_bits) - 1)
    for a, b in reversed(cfg.rounds):
        back = pow(a, -1, 1 << cfg.universe_bits)
        x = ((x - np.uint64(b)) * np.uint64(back)) & mask
        x = x ^ (x >> np.uint64(cfg.universe_bits // 2))  # its own inverse: twice the shift is the whole width
    return pa.array(x.astype(np.int64))


def g_inverse(values: str, cfg: Cfg) -> Column:
    """The elements that g maps to ``values`` (mulshift only)."""
    if cfg.g != "mulshift":
        raise ValueError("only mulshift is inverted by arithmetic; join back on g otherwise")
    return column_kernel(__name__, "g_inverse_array", "long", cfg)(F.col(values))
