"""Sources and sinks: tables, flattening, rule pools, verdicts, and a corpus of many small tables."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def load(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None) -> DataFrame:
    """Parquet, ORC, JSON or CSV (with a header); without a schema CSV types are inferred."""
    reader = spark.read.schema(schema) if schema else spark.read
    if kind == "csv":
        return reader.option("header", True).option("inferSchema", schema is None).csv(path)
    return reader.format(kind).load(path)


def with_row_address(df: DataFrame) -> DataFrame:
    """The file and the row within it, for a scan of Parquet: a stable address without a shuffle."""
    return df.select("*", F.col("_metadata.file_path").alias("row_file"), F.col("_metadata.row_index").alias("row_index"))


def flatten(df: DataFrame, json_columns: dict[str, Sequence[str]] | None = None) -> DataFrame:
    """Struct fields, given JSON keys and array sizes as columns of their own."""
    out = []
    for f in df.schema.fields:
        if isinstance(f.dataType, T.StructType):
            out += [F.col(f"`{f.name}`.`{g.name}`").alias(f"{f.name}_{g.name}") for g in f.dataType.fields]
        elif isinstance(f.dataType, T.ArrayType):
            out.append(F.size(f.name).alias(f"{f.name}_size"))
        else:
            out.append(F.col(f"`{f.name}`"))
            out += [F.get_json_object(f.name, f"$.{k}").alias(f"{f.name}_{k}") for k in (json_columns or {}).get(f.name, ())]
    return df.select(*out)


def write_verdicts(verdicts: DataFrame, path: str, kind: str = "parquet") -> None:
    verdicts.write.mode("overwrite").partitionBy("kind").format(kind).save(path)


def check_constraints(verdicts: DataFrame) -> DataFrame:
    """(cand_id, sql): reliable rules as check constraints; a value dependency is a comment, for it is none of one row."""
    sql = F.when(F.col("kind") == "FD", F.concat(F.lit("-- "), "rule")).otherwise(F.concat(F.lit("CHECK ("), "rule", F.lit(")")))
    return verdicts.where("reliable").select("cand_id", sql.alias("sql"))


def condition(rel) -> str:
    """The SQL condition of an arithmetic or string rule on a row."""
    from relmine.functions.expressions import sql_text

    return f"{sql_text(rel.expr)} = {rel.output}"


def relations_view(spark: SparkSession, rels: Sequence, name: str = "relations") -> DataFrame:
    """Rules as the temporary view ``name`` (cand_id, kind, inputs, output, arity, rule, condition)."""
    rows = [(r.cand_id, r.kind, list(r.inputs), r.output, r.arity, r.text, None if r.kind == "FD" else condition(r)) for r in rels]
    df = spark.createDataFrame(rows, "cand_id string, kind string, inputs array<string>, output string, arity int, rule string, condition string")
    df.createOrReplaceTempView(name)
    return df


def satisfaction_template(rels: Sequence, table: str) -> str:
    """SQL that counts the rows of ``table`` that satisfy each rule, in one scan; a row that is null on either side violates."""
    sums = ", ".join(f"sum(case when {condition(r)} then 1 else 0 end) as h{i}" for i, r in enumerate(rels))
    rows = " union all ".join("select '" + r.text.replace("'", "''") + f"' as rule, h{i} as hits, n as n_rows from counted" for i, r in enumerate(rels))
    return f"with counted as (select count(*) as n, {sums} from {table}) {rows}"


def violations_template(rel, table: str) -> str:
    """SQL for the rows of ``table`` that violate a rule."""
    return f"select * from {table} where not coalesce({condition(rel)}, false)"


def write_pool(rels, spark: SparkSession, path: str) -> None:
    """A pool of rules as Parquet; trees as text."""
    spark.createDataFrame([(r.kind, list(r.inputs), r.output, repr(r.expr)) for r in rels], "kind string, inputs array<string>, output string, expr string").write.mode("overwrite").parquet(path)


def read_pool(spark: SparkSession, path: str) -> list:
    from ast import literal_eval

    from relmine.model import Relation

    return [Relation(r["kind"], tuple(r["inputs"]), r["output"], literal_eval(r["expr"])) for r in spark.read.parquet(path).collect()]


class CorpusSource(DataSource):
    """Many small delimited files as one long table (table_id, row, cells); one partition for ``batch`` files.

    Options: ``path`` (a folder), ``batch`` (64), ``delimiter``.
    """

    @classmethod
    def name(cls) -> str:
        return "table_corpus"

    def schema(self) -> str:
        return "table_id string, row bigint, cells map<string,string>"

    def reader(self, schema: T.StructType) -> DataSourceReader:
        return _CorpusReader(self.options)


class _CorpusReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.batch, self.delimiter = options["path"], int(options.get("batch", "64")), options.get("delimiter", ",")

    def partitions(self) -> list[InputPartition]:
        from pathlib import Path

        files = sorted(str(p) for p in Path(self.path).glob("*.csv"))
        return [InputPartition(files[i:i + self.batch]) for i in range(0, len(files), self.batch)]

    def read(self, partition: InputPartition):
        import csv
        from pathlib import Path

        for name in partition.value:
            with open(name, newline="", encoding="utf-8") as f:
                for i, row in enumerate(csv.DictReader(f, delimiter=self.delimiter)):
                    yield Path(name).stem, i, {k: v for k, v in row.items() if k is not None and isinstance(v, str)}
