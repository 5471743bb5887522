from pyspark.sql import functions as F

from relmine import catalog
from relmine.sources.tables import load
from relmine.streaming import monitor


def test_stream_equals_batch_and_drops_late_rows(spark, small, tmp_path):
    e = catalog._events(spark, small).select("event_id", "user_id", "ts", "k", "seen")
    days = e.withColumn("day", F.to_date("ts"))
    last = days.agg(F.max("day")).first()[0]
    e.where(F.to_date("ts") < F.lit(last)).coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = monitor.windowed(monitor.replay(spark, str(tmp_path / "in"), e.schema), [catalog._PROPS], "1 day", late="1 hour")
    monitor.run_to_table(stream, str(tmp_path / "cp"), str(tmp_path / "out"))
    late = e.limit(1).withColumn("ts", F.to_timestamp_ntz(F.lit("2000-01-01 00:00:00")))
    e.where(F.to_date("ts") == F.lit(last)).unionByName(late).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    monitor.run_to_table(stream, str(tmp_path / "cp"), str(tmp_path / "out"))
    got = {r["window_start"]: (r["hits"], r["n_rows"]) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    want = {r["window_start"]: (r["hits"], r["n_rows"]) for r in monitor.windowed(e, [catalog._PROPS], "1 day", late=None).collect()}
    assert got and all(want[k] == v for k, v in got.items())
    assert len(got) >= len(want) - 1


def test_alarms(spark, small):
    w = monitor.windowed(catalog._events(spark, small), [catalog._PROPS], "1 day", late=None)
    assert monitor.alarms(w, 1.0).count() > 0 and monitor.alarms(w, 0.0).count() == 0


def test_entry_and_catalogue():
    import __spark_entry__ as entry

    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 70


def test_load_prunes(spark, small):
    assert load(spark, small, "nation", ["n_name"]).columns == ["n_name"]
