"""Intermediates are written in a number of files that follows the cores, not the partitions."""

import glob

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from relmine.llm import common


def files(df):
    return glob.glob(df._saved_at.removeprefix("file:") + "/part-*")


def most(spark):
    return common.FILES * spark.sparkContext.defaultParallelism


def test_many_partitions_make_few_files_of_the_same_rows(spark):
    out = common.saved(spark.range(0, 5000, 1, 97).repartition(97, "id"), "few")
    assert len(files(out)) <= most(spark) < 97
    assert sorted(r.id for r in out.collect()) == list(range(5000))


def test_each_partition_passes_python_alone(spark):
    """Partitions that one task writes are sorted each by itself; a function over sorted batches sees one of them at a time."""
    def run(batches):
        seen = np.concatenate([b.column(0).to_numpy() for b in batches] or [np.zeros(0, np.int64)])
        yield pa.RecordBatch.from_arrays([pa.array([len(seen)]), pa.array([int((np.diff(seen) >= 0).all())])], names=["n", "ordered"])

    parts = spark.range(0, 20_000, 1, 8).select((F.col("id") % 500).alias("key")).repartition(97, "key").sortWithinPartitions("key")
    out = common.saved(parts.mapInArrow(run, "n long, ordered long"), "alone")
    rows = out.collect()
    assert len(files(out)) <= most(spark) < len(rows)
    assert sum(r.n for r in rows) == 20_000 and all(r.ordered for r in rows)


def test_components_of_a_long_chain_over_many_partitions(spark):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "61")
    try:
        edges = spark.createDataFrame([(i, i + 1) for i in range(1, 200)] + [(1000, 1001)], "u long, v long")
        out = common.components(edges)
        assert len(files(out)) <= most(spark)
        assert {r.node: r.root for r in out.collect()} == {i: 1 for i in range(2, 201)} | {1001: 1000}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
