"""The Independence Test counts numbers as numbers, and what it counts stays the same."""

from pyspark.sql import functions as F
from test_one_draw import numbers

from relmine.catalog import ar
from relmine.model import Config
from relmine.operators import independence


def test_numbers_are_counted_as_their_texts(spark):
    df = numbers(spark, 2000).withColumn("t", F.col("b").cast("string"))
    rels, cfg = [ar("+", "a", "d", "e"), ar("+", "b", "d", "c")], Config(setting="dirty")
    text = df.select(*(F.col(c).cast("string").alias(c) for c in df.columns))
    rows = lambda frame: sorted(map(tuple, frame.collect()))
    assert rows(independence.totals(df, df.columns)) == rows(independence.totals(text, df.columns))
    left = {r.cand_id: [c for c in df.columns if c not in (*r.columns, "t")] for r in rels}
    bad = lambda r: df.where(~independence.holds(r, cfg=cfg)).select(F.inline(independence._pairs(left[r.cand_id]))).groupBy("col", "value").count()
    want = sorted((r.cand_id, *x) for r in rels for x in map(tuple, bad(r).collect()))
    assert rows(independence.violating(df, rels, left, cfg)) == want
    plan = independence.totals(df, ["a", "b"])._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate [c#" in plan and "v#" in plan
