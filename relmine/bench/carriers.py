"""Tables that carry known rules, derived from the given ones, and deterministic noise."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relmine.functions.statistics import hash_int
from relmine.sources.tables import load

MONEY = ("qty", "ext_c", "unit_c", "dp", "tp", "disc_c", "net_c", "tax_c", "gross_c", "list_c", "ship_c", "total_c", "sur_c", "due_c")


def ar_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines in whole cents, with the columns that their formulas make."""
    whole = lambda c, by=1: F.round(F.col(c) * by).cast("bigint")
    div = lambda c, d: F.expr(f"({c}) div {d}")
    lines = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice"), "l_partkey")
    base = lines.select(
        "l_orderkey", "l_linenumber", "l_partkey", whole("l_quantity").alias("qty"), whole("l_extendedprice", 100).alias("ext_c"), whole("p_retailprice", 100).alias("unit_c"),
        whole("l_discount", 100).alias("dp"), whole("l_tax", 100).alias("tp"))
    flag = lambda cond: F.expr(f"case when {cond} then 1 else 0 end").cast("bigint")
    return (base.withColumn("disc_c", div("ext_c * dp + 50", 100)).withColumn("net_c", F.expr("ext_c - disc_c")).withColumn("tax_c", div("net_c * tp + 50", 100))
            .withColumn("gross_c", F.expr("net_c + tax_c")).withColumn("list_c", F.expr("qty * unit_c")).withColumn("ship_c", F.expr("500 * qty"))
            .withColumn("total_c", F.expr("net_c + tax_c + ship_c")).withColumn("sur_c", F.expr("case when l_partkey % 20 = 3 then 700 else 0 end").cast("bigint"))
            .withColumn("due_c", F.expr("gross_c + sur_c")).withColumn("a_flag", flag("qty = 50")).withColumn("b_flag", flag("dp = 0 and tp = 0"))
            .withColumn("e_flag", flag("l_linenumber = 7 and l_partkey % 50 = 0")).withColumn("zero_c", F.lit(0).cast("bigint")))


def st_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = F.split("p_name", " ")
    return load(spark, sf_dir, "part").select("p_partkey", "p_name", words[0].alias("w1"), words[1].alias("w2"), "p_brand", "p_type")


def st_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority", F.substring_index("o_orderpriority", "-", 1).alias("prio_code"), F.regexp_replace("o_orderpriority", "^[^-]*-", "").alias("prio_text"),
                                                F.date_format("o_orderdate", "yyyy-MM").alias("ym"), F.date_format("o_orderdate", "yyyy").alias("y"), F.date_format("o_orderdate", "MM").alias("m"))


def st_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    piece = lambda n: F.split_part("url", F.lit("/"), F.lit(n))
    return load(spark, sf_dir, "pages").select("page_id", "url", piece(3).alias("host"), F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("page_lang"))


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The star of order lines with its dimensions; sizes decide how each is joined."""
    t = lambda n: load(spark, sf_dir, n)
    supplier = t("supplier").join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return (t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
            .join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
            .select("l_orderkey", "l_partkey", "s_suppkey", "o_custkey", "n_name", "r_name", "p_brand", "p_type", "o_orderstatus", "c_mktsegment", "c_nationkey", "l_returnflag", "l_linestatus", "l_linenumber"))


def noisy(df: DataFrame, rate: float, columns: Sequence[str], keys: Sequence[str], seed: int = 42) -> DataFrame:
    """``rate`` of the rows, picked by a hash of their keys, get one cell of ``columns`` changed by a hashed amount.

    One cell per row: cell-wise noise on three columns would leave a rule 0.9 ^ 3 of its rows.
    """
    pick = hash_int(*(F.col(k) for k in keys), F.lit(f"pick{seed}")) % 1000 < int(rate * 1000)
    which = hash_int(*(F.col(k) for k in keys), F.lit(f"col{seed}")) % len(columns)
    amount = hash_int(*(F.col(k) for k in keys), F.lit(f"amt{seed}")) % 9973 + 1
    return df.withColumns({c: F.when(pick & (which == i), F.col(c) + amount).otherwise(F.col(c)) for i, c in enumerate(columns)})


def mixed_up(df: DataFrame, rate: float, columns: Sequence[str], keys: Sequence[str], seed: int = 42, most: int = 256) -> DataFrame:
    """``rate`` of the rows, picked by a hash of their keys, get one cell of ``columns`` replaced by another value of its column.

    Each column offers the ``most`` values with the smallest hashes, so what is gathered does not grow with the rows.
    """
    cells = df.select(F.inline(F.array(*(F.struct(F.lit(i).alias("i"), F.col(c).cast("string").alias("v")) for i, c in enumerate(columns))))).where("v is not null").distinct()
    nth = F.row_number().over(Window.partitionBy("i").orderBy(hash_int(F.col("v"), F.lit(f"val{seed}")), "v"))
    offered: dict[int, list[str]] = {}
    for r in cells.withColumn("nth", nth).where(F.col("nth") <= most).orderBy("i", "nth").collect():
        offered.setdefault(r["i"], []).append(r["v"])
    of_row = lambda tag: hash_int(*(F.col(k) for k in keys), F.lit(f"{tag}{seed}"))
    pick, which, kinds, new = of_row("pick") % 1000 < int(rate * 1000), of_row("col") % len(columns), dict(df.dtypes), {}
    for i, c in enumerate(columns):
        if len(values := offered.get(i, [])) > 1:
            at = lambda by: F.array(*map(F.lit, values))[((of_row("val") + by) % len(values)).cast("int")].cast(kinds[c])  # noqa: E731, B023
            new[c] = F.when(pick & (which == i), F.when(at(0).eqNullSafe(F.col(c)), at(1)).otherwise(at(0))).otherwise(F.col(c))
    return df.withColumns(new) if new else df


def sized(df: DataFrame, rows: int, order: Sequence[str]) -> DataFrame:
    """``rows`` rows by hash order; a smaller table is repeated until it has them."""
    n = df.count()
    if n == 0:
        return df
    times = -(-rows // n)
    many = df if times <= 1 else df.withColumn("_i", F.explode(F.sequence(F.lit(1), F.lit(times))))
    key = F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in order)))
    return many.withColumn("_k", key).orderBy(*(["_i"] if times > 1 else []), "_k", *order).limit(rows).select(*df.columns)
