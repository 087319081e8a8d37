"""Sets from event streams: windows, intersections within windows, and an index kept fresh."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wordset.config import Cfg
from wordset.functions import hashing
from wordset.functions.store import new_path
from wordset.operators import groups as G
from wordset.plans.sizing import small_side
from wordset.sources.tables import SCHEMAS


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Events as a stream from a folder of Parquet files, or one file of its folder. Watermarks need a timestamp with a zone,
    so ``ts`` is cast."""
    reader = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_trigger)
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isFile():
        reader, path = reader.option("pathGlobFilter", p.getName()), p.getParent().toString()
    raw = reader.parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_sets(events: DataFrame, watermark: str = "1 hour", key: str = "event_type", elem: str = "user_id") -> DataFrame:
    """``ts, set_id, elem`` with repeats within the watermark dropped."""
    rows = events.select("ts", F.col(key).cast("string").alias("set_id"), F.col(elem).cast("long").alias("elem")).dropna()
    return rows.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["set_id", "elem"])


def window_sets(events: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str | None = None, gap: str = "1 hour", watermark: str = "1 hour") -> DataFrame:
    """``start, end, set_id, elem, freq`` per window: ``tumbling``, ``sliding`` or ``session`` (one per set and element)."""
    if kind not in ("tumbling", "sliding", "session"):
        raise ValueError("kind must be tumbling, sliding or session")
    w = F.session_window("ts", gap) if kind == "session" else F.window("ts", size, slide if kind == "sliding" else None)
    rows = events.withWatermark("ts", watermark).groupBy(w.alias("w"), F.col("event_type").alias("set_id"), F.col("user_id").alias("elem")).agg(F.count(F.lit(1)).alias("freq"))
    return rows.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "set_id", "elem", "freq")


def stream_intersect(events: DataFrame, types: list[str], size: str = "1 day", watermark: str = "1 hour") -> DataFrame:
    """``start, elem``: users with events of every type in a window. Each user's types are one word, a bit per type, so the
    k-way intersection is one aggregate."""
    if not 1 <= len(types) <= 63:
        raise ValueError("1 to 63 event types")
    bit = F.expr("case event_type " + " ".join(f"when '{t}' then {1 << i}L" for i, t in enumerate(types)) + " else 0L end")
    rows = events.withWatermark("ts", watermark).groupBy(F.window("ts", size).alias("w"), F.col("user_id").alias("elem")).agg(F.bit_or(bit).alias("mask"))
    return rows.filter(F.col("mask") == (1 << len(types)) - 1).select(F.col("w.start").alias("start"), "elem")


def stream_join(left: DataFrame, right: DataFrame, within: str = "1 hour", watermark: str = "1 hour") -> DataFrame:
    """Pairs of events of a user, the right one at most ``within`` after the left one."""
    a = left.withWatermark("ts", watermark).select(F.col("user_id").alias("elem"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_id"))
    b = right.withWatermark("ts", watermark).select(F.col("user_id").alias("b_elem"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_id"))
    return a.join(b, (F.col("elem") == F.col("b_elem")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {within}"))).drop("b_elem")


def stream_probe(events: DataFrame, stored: DataFrame, key: str = "user_id") -> DataFrame:
    """Events whose key is in a stored set, by a stream-static semi join."""
    return events.join(small_side(stored.select(F.col("elem").alias(key)).distinct()), key, "left_semi")


def merge_index_batch(spark: SparkSession, index_path: str, cfg: Cfg):
    """A ``foreachBatch`` function that adds ``(set_id, elem)`` rows to the group table at ``index_path``, or takes them away where a
    column ``gone`` is true (a member both added and taken away in one batch goes).

    Only sets of the batch are touched, and these are cut anew: a deletion can't be taken out of an image. Versions are written beside each other and a pointer names the last, so a failed
    batch leaves the old one, and the same batch twice gives the same index."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        s = batch.sparkSession
        gone = batch.filter(F.coalesce("gone", F.lit(False))).select("set_id", "elem").distinct() if "gone" in batch.columns else None
        fresh = batch.select("set_id", "elem").distinct()
        last = _version(s, index_path)
        if last is None:
            G.build(fresh if gone is None else fresh.exceptAll(gone), cfg).groups.write.mode("overwrite").parquet(f"{index_path}/v={batch_id}")
        else:
            old = s.read.parquet(f"{index_path}/v={last}")
            touched = fresh.select("set_id").distinct()
            known = old.join(touched, "set_id", "left_semi").select("set_id", F.explode("elems.elem").alias("elem"))
            members = known.unionByName(fresh).distinct()
            rebuilt = G.build(members if gone is None else members.join(gone, ["set_id", "elem"], "left_anti"), cfg).groups
            kept = old.join(touched, "set_id", "left_anti")
            kept.unionByName(rebuilt).write.mode("overwrite").parquet(f"{index_path}/v={batch_id}")
        s.createDataFrame([(batch_id,)], "v long").coalesce(1).write.mode("overwrite").json(f"{index_path}/_last")

    return merge


def _version(spark: SparkSession, path: str) -> int | None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(f"{path}/_last")
    if not p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p):
        return None
    return spark.read.schema("v long").json(f"{path}/_last").first()[0]


def read_index(spark: SparkSession, index_path: str) -> DataFrame:
    return spark.read.parquet(f"{index_path}/v={_version(spark, index_path)}")


def image_state(events: DataFrame, cfg: Cfg = Cfg(m=1), t: int = 3, watermark: str = "1 hour") -> DataFrame:
    """Per event type and prefix of t bits of its users a word image and a count, kept in the state store: ``set_id, z, img, n``.

    A stateful operator of our own: an image is updated from whole batches of the hash values that Spark computes, and never forgotten."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key, frames, state: GroupState):
        img, n = state.get if state.exists else (0, 0)
        for f in frames:
            n += len(f)
            img |= int(np.bitwise_or.reduce(np.left_shift(np.int64(1), f["y_1"].to_numpy(np.int64)), initial=0))
        state.update((img, n))
        yield pd.DataFrame({"set_id": [key[0]], "z": [key[1]], "img": [img], "n": [n]})

    rows = events.withWatermark("ts", watermark).select(F.col("event_type").alias("set_id"), F.col("user_id").alias("elem"))
    rows = G.hashed(rows, cfg, 1).withColumn("z", F.expr(hashing.prefix_sql("g", t, cfg)))
    return rows.select("set_id", "z", "y_1").groupBy("set_id", "z").applyInPandasWithState(update, "set_id string, z long, img long, n long", "img long, n long", "update", GroupStateTimeout.NoTimeout)


def run_once(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """All that is there now through a streaming query, into a Parquet table in the shared folder.

    A batch is a folder of its own, written over if the batch is run again; in ``complete`` mode the last one is the result."""
    spark = df.sparkSession
    where = new_path(spark, f"stream-{name}")

    def sink(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/rows/{'all' if mode == 'complete' else f'batch={batch_id}'}")

    q = df.writeStream.foreachBatch(sink).outputMode(mode).option("checkpointLocation", f"{where}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    if mode == "complete":
        return spark.read.schema(df.schema).parquet(f"{where}/rows/all")
    return spark.read.schema(df.schema).option("recursiveFileLookup", "true").parquet(f"{where}/rows")


def late_policy(path: str, allowed: str = "1 hour"):
    """A ``foreachBatch`` function that keeps late events apart instead of dropping them: ``path/on_time`` has events no more than ``allowed`` behind
    the latest one of the batches before, ``path/late`` the others, to be merged by a batch job. Run again, a batch gives the same files."""

    def split(batch: DataFrame, batch_id: int) -> None:
        s = batch.sparkSession
        marks = f"{path}/latest"
        p = s.sparkContext._jvm.org.apache.hadoop.fs.Path(marks)
        known = s.read.parquet(marks).filter(F.col("batch") < batch_id).agg(F.max("ts")).first()[0] if p.getFileSystem(s.sparkContext._jsc.hadoopConfiguration()).exists(p) else None
        late = F.lit(False) if known is None else F.coalesce(F.col("ts") < F.lit(known) - F.expr(f"interval {allowed}"), F.lit(False))
        for name, rows in (("late", batch.filter(late)), ("on_time", batch.filter(~late))):
            rows.write.mode("overwrite").parquet(f"{path}/{name}/batch={batch_id}")
        batch.agg(F.max("ts").alias("ts")).write.mode("overwrite").parquet(f"{marks}/batch={batch_id}")

    return split
