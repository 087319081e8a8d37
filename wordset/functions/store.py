"""Tables that cut lineage: written to the folder that all executors share, then read again."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: dict[str, str] = {}
_seen: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session. Where that is unset: a temporary folder in local mode; on a cluster an error, since
    no other folder is known to be shared."""
    if base := spark.conf.get("spark.checkpoint.dir", None):
        return base
    app = spark.sparkContext.applicationId
    if app not in _own:
        local = spark.sparkContext.master.split("[")[0] == "local"
        if not local:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        _own[app] = f"file://{tempfile.mkdtemp(prefix='wordset-')}"
    return _own[app]


def new_path(spark: SparkSession, name: str) -> str:
    top = f"{shared_dir(spark)}/wordset/{spark.sparkContext.applicationId}"
    if top not in _seen:
        _seen.add(top)
        local = top.removeprefix("file://")
        if spark.sparkContext.master.split("[")[0] == "local" and local.startswith("/"):  # nobody else reads these tables
            atexit.register(shutil.rmtree, local, ignore_errors=True)
    return f"{top}/{name}-{uuid.uuid4().hex[:12]}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a Parquet table in the shared folder: computed once, and not lost with an executor."""
    spark = df.sparkSession
    df.write.parquet(path := new_path(spark, name))
    return spark.read.schema(df.schema).parquet(path)


def drop_written(df: DataFrame) -> None:
    """Deletes the files of a table that ``written`` made, once nothing reads it any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    for f in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(f)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def clean(spark: SparkSession) -> None:
    """Deletes every table this application has written here; results that still read one are void."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/wordset/{spark.sparkContext.applicationId}")
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def free_name(df: DataFrame, name: str) -> str:
    """``name``, with as many underscores before it as make it unlike every column of ``df``, whatever the case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name
