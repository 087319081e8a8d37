"""The methods on stored structures: pre-processing once, then queries, as a served index works and as the experiments time it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from wordset.functions.store import written
from wordset.operators import baselines, blocks, fixed, prefix, probe, scan
from wordset.operators import groups as G
from wordset.queries import CFG, PAIRS, QUADS, TRIPLES, _small_3, _small_big, frames
from wordset.sources import families as fam


def served(spark: SparkSession, d: str) -> tuple[dict[str, Callable[[], object]], Callable[[dict], dict[str, Callable[[], DataFrame]]]]:
    """Builders of the stored structures by name, to be timed as pre-processing, and, given what they made, the queries on them."""
    f1 = lambda: fam.supp_orders(spark, d)
    uneven = lambda: fam.part_orders(spark, d).unionByName(fam.flag_orders(spark, d))
    build: dict[str, Callable[[], object]] = {"lists": lambda: baselines.stored(f1()), "uneven_lists": lambda: baselines.stored(uneven())}
    build["fixed"] = lambda: (written(fixed.build(f1(), CFG), "fixed"), written(G.set_stats(f1()), "sizes"))
    build["prefix"] = lambda: prefix.build(f1(), CFG, keep=True)
    for m in (1, 2, 4):
        build[f"scan_{m}"] = lambda m=m: G.build(f1(), CFG.with_(m=m), keep=True)
    for codec in ("plain", "lowbits"):
        build[f"blocks_{codec}"] = lambda c=codec: (written(blocks.build_blocks(f1(), CFG, m=2, codec=c).repartitionByRange("c", "set_id"), "blocks"), written(blocks.block_stats(f1()), "sizes"))

    def queries(have: dict) -> dict[str, Callable[[], DataFrame]]:
        lists, uneven_, fixed_, prefix_ = have["lists"], have["uneven_lists"], have["fixed"], have["prefix"]
        q = {k: frames(lists, names) for k, names in ((2, PAIRS), (3, TRIPLES), (4, QUADS))}
        small, small3 = frames(lists, _small_big), frames(lists, _small_3)
        kernel = lambda method, k, codec="plain": lambda: blocks.run_stored(*have[f"blocks_{codec}"], q[k], CFG, method, 2, codec)
        out = {
            "m1_pair": lambda: fixed.intersect_stored(*fixed_, q[2], CFG),
            "m2_pair": lambda: scan.intersect_by_bits(prefix_, q[2]),
            "m2_k3": lambda: scan.intersect_by_bits(prefix_, q[3]),
            "m2_k4": lambda: scan.intersect_by_bits(prefix_, q[4]),
            "m3_m1": lambda: scan.intersect(have["scan_1"], q[2]),
            "m3_m2": lambda: scan.intersect(have["scan_2"], q[2]),
            "m3_m4": lambda: scan.intersect(have["scan_4"], q[2]),
            "m3_k3": lambda: scan.intersect(have["scan_2"], q[3]),
            "m3_k4": lambda: scan.intersect(have["scan_2"], q[4]),
            "m3_blocks_pair": kernel("scan", 2),
            "m3_blocks": kernel("scan", 3),
            "m3_blocks_k4": kernel("scan", 4),
            "m3_lowbits": kernel("scan", 2, "lowbits"),
            "m4_pair": lambda: probe.intersect(uneven_, small, CFG),
            "m4_k3": lambda: probe.intersect(uneven_, small3, CFG),
            "base_merge_pair": lambda: baselines.merge(lists, q[2]),
            "base_merge": lambda: baselines.merge(lists, q[3]),
            "base_merge_k4": lambda: baselines.merge(lists, q[4]),
            "base_merge_uneven": lambda: baselines.merge(uneven_, small),
            "base_hash": lambda: baselines.hashing_(lists, q[3]),
            "base_svs": lambda: baselines.smallest_first(lists, q[3]),
            "base_lookup": lambda: baselines.lookup(lists, q[3], CFG),
            "base_packed": lambda: baselines.packed_codes(lists, q[3], CFG),
        }
        return out | {f"kernel_{m}": kernel(m, 3) for m in ("merge", "hash", "lookup", "svs", "adaptive")}

    return build, queries
