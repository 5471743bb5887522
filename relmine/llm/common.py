"""Shared plumbing: table access, saved intermediates and connected components."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Shuffle files of a write are of no use once it is done, for what it wrote is read from then on.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
_CODEC = "spark.sql.parquet.compression.codec"
#: A file system without native code starts a process of the executor for each file that it creates, so intermediates are
#: written in so many files for each core at most; row groups of so many bytes keep a writer's buffer small and a file divisible.
FILES, ROW_GROUP = 2, 16 << 20
_paths: dict[int, str] = {}
#: what ``saved`` has written and not yet deleted, in order
_written: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: the session's checkpoint folder.

    A local master may do without; on a cluster there is no safe place to guess, so an unset one is an error.
    """
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if where is None:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="relmine-"))
        where = spark.sparkContext.getCheckpointDir()
    return where


def scratch_dir(spark: SparkSession) -> str:
    """This application's part of the shared folder; it goes when the driver ends, or with ``clean``."""
    path = f"{shared_dir(spark)}/relmine-{spark.sparkContext.applicationId}"
    if id(spark.sparkContext) not in _paths:
        _paths[id(spark.sparkContext)] = path
        atexit.register(clean, spark)
    return path


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def clean(spark: SparkSession) -> None:
    """Delete all intermediates of this application; results that were not written or collected are lost."""
    with contextlib.suppress(Exception):  # a session that has ended has no file system left to ask
        if path := _paths.pop(id(spark.sparkContext), None):
            _written[:] = [x for x in _written if not x.startswith(path)]
            _delete(spark, path)


def saved(df: DataFrame, label: str, batch: int | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back, which cuts its lineage.

    A task writes what several partitions give, one after the other, where there are many more of them than cores.
    ``batch`` is the number of rows that pass between Spark and Python at once, to be set where rows are large.
    """
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{label}-{uuid.uuid4().hex}"
    wanted = {_CLEANUP: "true", _CODEC: "zstd"} | ({_BATCH: str(batch)} if batch else {})
    before = {k: spark.conf.get(k, None) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        df.coalesce(FILES * spark.sparkContext.defaultParallelism).write.option("parquet.block.size", ROW_GROUP).parquet(path)
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)
    _written.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._saved_at = path
    return out


def dropped(*frames: DataFrame) -> None:
    """Delete what ``saved`` wrote for ``frames``, once nothing reads it any more."""
    for df in frames:
        if (path := getattr(df, "_saved_at", None)) in _written:
            _written.remove(path)
            _delete(df.sparkSession, path)


def mark() -> int:
    """A point in the order of what is saved, for ``release``."""
    return len(_written)


def release(spark: SparkSession, since: int, *keep: DataFrame) -> None:
    """Delete what was saved after the mark, but for what ``keep`` reads."""
    kept = {getattr(df, "_saved_at", None) for df in keep}
    for path in [x for x in _written[since:] if x not in kept]:
        _written.remove(path)
        _delete(spark, path)


def superseded(spark: SparkSession, docs: DataFrame) -> None:
    """Delete all that was saved before and that ``docs`` does not read: what earlier stages needed whose results are written."""
    read = docs.inputFiles()
    for path in [x for x in _written if not any(x.rsplit("/", 1)[1] in f for f in read)]:
        _written.remove(path)
        _delete(spark, path)


def text_key():
    """Rows are joined back on (doc_id, this hash): repeated ids with other texts stay apart."""
    return F.xxhash64(F.coalesce(F.col("text"), F.lit("")), F.col("text").isNull())


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of ``edges(u, v)``: rows (node, root), root the smallest node.

    Alternates a star step over larger and over smaller neighbours until the
    edge set is a forest of depth one. Minima are combined before the shuffle
    and written, so that both sides of each join are plain shuffles that AQE may
    split: a hub does not meet in one task. Nodes without edges are not returned.
    """
    big, small = F.greatest("u", "v"), F.least("u", "v")
    e = saved(edges.select(big.alias("u"), small.alias("v")).where("u <> v").distinct(), "edges")
    before = None
    for _ in range(max_rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        near = saved(both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m")), "near")
        large = saved(both.join(near, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
                      .where("u <> v").distinct(), "large")
        low = saved(large.groupBy("u").agg(F.min("v").alias("m")), "low")
        joined = large.join(low, "u")
        star = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(
            low.select("u", F.col("m").alias("v")))
        after = saved(star.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
        dropped(e, near, large, low)
        e = after
        now = e.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        if now == before:
            out = e.select(F.col("u").alias("node"), F.col("v").alias("root"))
            out._saved_at = e._saved_at
            return out
        before = now
    raise RuntimeError("components did not converge")
