"""Accuracy and cost measures over labelled pools."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def pr_curve(scores: DataFrame) -> DataFrame:
    """(method, score, tp, fp, positives, precision, recall) of (method, score, label): a point per different score."""
    y = F.col("label").cast("int")
    points = scores.groupBy("method", "score").agg(F.sum(y).alias("p"), F.sum(1 - y).alias("q"))
    down = Window.partitionBy("method").orderBy(F.desc("score")).rowsBetween(Window.unboundedPreceding, 0)
    total = scores.groupBy("method").agg(F.sum(y).alias("positives"))
    run = points.select("method", "score", F.sum("p").over(down).alias("tp"), F.sum("q").over(down).alias("fp")).join(total, "method")
    return run.withColumn("precision", F.col("tp") / (F.col("tp") + F.col("fp"))).withColumn("recall", F.try_divide("tp", "positives"))


def pr_auc(scores: DataFrame, rule: str = "step") -> DataFrame:
    """(method, pr_auc): average precision, or the trapezoid with the first point drawn to recall 0."""
    order = Window.partitionBy("method").orderBy(F.desc("score"))
    c = pr_curve(scores).withColumn("r0", F.coalesce(F.lag("recall").over(order), F.lit(0.0))).withColumn("p0", F.coalesce(F.lag("precision").over(order), F.col("precision")))
    height = F.col("precision") if rule == "step" else (F.col("precision") + F.col("p0")) / 2
    return c.groupBy("method").agg(F.sum((F.col("recall") - F.col("r0")) * height).alias("pr_auc"))


def prf(scores: DataFrame, threshold: float) -> DataFrame:
    """(method, tp, fp, fn, precision, recall, f1) where a score of at least ``threshold`` is a yes."""
    yes, y = F.col("score") >= threshold, F.col("label")
    c = scores.groupBy("method").agg(F.count_if(yes & y).alias("tp"), F.count_if(yes & ~y).alias("fp"), F.count_if(~yes & y).alias("fn"))
    p, r = F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")), F.try_divide(F.col("tp"), F.col("tp") + F.col("fn"))
    return c.withColumn("precision", F.coalesce(p, F.lit(0.0))).withColumn("recall", F.coalesce(r, F.lit(0.0))).withColumn("f1", F.coalesce(F.try_divide(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0)))


def best_f1(scores: DataFrame) -> DataFrame:
    """(method, threshold, precision, recall, f1) at the threshold of the largest F1, the highest of equals."""
    f1 = F.coalesce(F.try_divide(2 * F.col("tp"), F.col("tp") + F.col("fp") + F.col("positives")), F.lit(0.0))
    c = pr_curve(scores).withColumn("f1", f1)
    return c.groupBy("method").agg(F.max(F.struct("f1", F.col("score").alias("threshold"), "precision", "recall")).alias("b")).select("method", "b.threshold", "b.precision", "b.recall", "b.f1")


def summary(scores: DataFrame, ours: str = "framework") -> DataFrame:
    """(method, pr_auc, precision, recall, f1, gain): the last three of a threshold of the largest F1; gain is that of
    ``ours`` over the best other method."""
    auc = pr_auc(scores)
    best = auc.agg(F.max(F.when(~F.col("method").startswith(ours), F.col("pr_auc"))).alias("best"))
    gain = F.when(F.col("method") == ours, F.try_divide("pr_auc", "best") - 1)
    return auc.join(best_f1(scores), "method").join(F.broadcast(best), F.lit(True)).select("method", "pr_auc", "precision", "recall", "f1", gain.alias("gain"))


def timing_summary(times: DataFrame) -> DataFrame:
    """(method, p50, p90, p95, mean) of (method, ms)."""
    return times.groupBy("method").agg(*(F.percentile("ms", q / 100).alias(f"p{q}") for q in (50, 90, 95)), F.avg("ms").alias("mean"))


def optimization_counters(verdicts: DataFrame) -> DataFrame:
    """Shares of candidates that the bound rejects, and of sampled ones that stop early."""
    sampled = F.col("stop_reason").isin("wilson", "exhausted")
    tried = sampled | (F.col("stop_reason") == "bound")
    return verdicts.agg(F.count("*").alias("candidates"), F.try_divide(F.count_if(F.col("stop_reason") == "bound"), F.count_if(tried)).alias("bound_rejected"),
                        F.try_divide(F.count_if(F.col("stop_reason") == "wilson"), F.count_if(sampled)).alias("early_stopped"))


def relative_gain(aucs: DataFrame, ours: str) -> DataFrame:
    """(setting, own, best_baseline, gain) of (setting, method, pr_auc)."""
    is_own = F.col("method") == ours
    both = aucs.groupBy("setting").agg(F.max(F.when(is_own, F.col("pr_auc"))).alias("own"), F.max(F.when(~is_own, F.col("pr_auc"))).alias("best_baseline"))
    return both.withColumn("gain", F.try_divide("own", "best_baseline") - 1)
