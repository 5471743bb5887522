"""The Minimality Test: a rule goes if a retained rule with the same output needs only some of its inputs."""

from __future__ import annotations

from collections.abc import Iterable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relmine.model import Relation

SCHEMA = "cand_id string, kind string, inputs array<string>, output string, arity int, rule string"


def frame(spark: SparkSession, rels: Iterable[Relation]) -> DataFrame:
    return spark.createDataFrame([(r.cand_id, r.kind, sorted(r.inputs), r.output, r.arity, r.text) for r in rels], SCHEMA)


def minimal(candidates: DataFrame, pruners: DataFrame) -> DataFrame:
    """Candidates without a pruner; the pruners are as many as rules, never as rows, and sizes decide the join."""
    p = pruners.select(F.col("inputs").alias("p_inputs"), F.col("output").alias("p_output")).distinct()
    on = (F.col("output") == F.col("p_output")) & (F.size("p_inputs") < F.size("inputs")) & (F.size(F.array_except("p_inputs", "inputs")) == 0)
    return candidates.join(p, on, "left_anti")


def is_minimal(rel: Relation, pruners: Sequence[Relation]) -> bool:
    return not any(p.output == rel.output and set(p.inputs) < set(rel.inputs) for p in pruners)


def open_input_sets(sets: Iterable[frozenset[str]], output: str, pruners: Sequence[Relation]) -> list[frozenset[str]]:
    """Input sets that may still hold a minimal rule, before any expression is built."""
    mine = [set(p.inputs) for p in pruners if p.output == output]
    return [s for s in sets if not any(m < s for m in mine)]
