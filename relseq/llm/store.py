"""Shared storage for intermediate results.

Every table that must outlive its lineage is written as Parquet below ``spark.checkpoint.dir`` (a folder
that driver and executors share), so a lost executor never takes the only copy with it. Where a session on one
machine has no such folder (tests) a temporary one is set; on a cluster its absence is an error.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relseq.session import ship

CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
HOT_GROUPS = 10_000
_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; a local one is made only if the setting is absent."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = spark.sparkContext.getCheckpointDir()
        if not folder:
            if not spark.sparkContext.master.startswith("local"):
                raise ValueError("spark.checkpoint.dir has to name a folder that driver and executors share")
            folder = "file://" + tempfile.mkdtemp(prefix="relseq-")
            spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    if not _written:
        atexit.register(clean)
    path = f"{shared_dir(spark)}/relseq/{name}-{uuid.uuid4().hex[:12]}"
    _written.append((spark, path))
    return path


def materialise(df: DataFrame, name: str, compression: str = "zstd", few: bool = False) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, computes once. ``few``: small results of many
    tasks are brought together in a few files after they are computed."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df = df.hint("rebalance") if few else df
    # What was exchanged for the write is of no use after it; else it stays on disk until the driver collects garbage.
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.option("compression", compression).parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def with_groups(rows: DataFrame, groups: DataFrame, keys: list[str], total: int, hot_groups: int = HOT_GROUPS) -> DataFrame:
    """``rows`` with the columns of their group; rows without one go. ``groups`` has a row for each key with its
    size ``n``, and ``total`` is the sum of sizes: fewer than ``hot_groups`` groups can have more than that share of
    it, so these are broadcast and their rows stay where they are; all others are small."""
    if total < hot_groups:  # there are fewer groups than that, too
        return rows.join(F.broadcast(groups), keys).drop("n")
    hot, cool = groups.where(F.col("n") > total // hot_groups), groups.where(F.col("n") <= total // hot_groups)
    apart = rows.join(F.broadcast(hot), keys).drop("n")
    rest = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(cool, keys).drop("n")
    return apart.unionByName(rest)


def drop(df: DataFrame) -> None:
    """Delete the files behind a table that ``materialise`` returned and nobody reads any more."""
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/relseq/" in path:
            _delete(spark, path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def clean() -> None:
    """Remove what this process wrote; runs at exit, skipped where the session is already gone."""
    while _written:
        spark, path = _written.pop()
        if spark.sparkContext._jsc is None or spark.sparkContext._jsc.sc().isStopped():
            continue
        _delete(spark, path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, with Arrow batches kept small: texts are long, and workers hold whole batches."""
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_batches(spark: SparkSession, rows: int = 1000, size: str = "8m") -> None:
    ship(spark)
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) > rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", size)
