"""Queries that once made their rows up read the given tables and agree with their SQL."""

import duckdb
import pytest
from pyspark.errors import AnalysisException

from relmine import catalog
from relmine.sources.tables import load


@pytest.mark.parametrize("name", ["minimality_prune", "independence_golden", "wilson_grid"])
def test_rows_come_from_the_tables(spark, small, tmp_path, name):
    con = duckdb.connect()
    for t in ("lineitem", "part"):
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    got = catalog.QUERIES[name](spark, small)
    expected = con.execute(f"select {', '.join(got.columns)} from ({catalog.ORACLE_SQL[name]})").fetchall()
    assert sorted(map(tuple, got.collect())) == sorted(expected) and expected
    with pytest.raises(AnalysisException):
        catalog.QUERIES[name](spark, str(tmp_path)).collect()


def test_a_rule_that_fails_on_the_table_neither_stays_nor_prunes(spark, small, tmp_path):
    for t in ("lineitem", "part"):
        df = load(spark, small, t)
        (df.where("l_partkey % 20 = 3") if t == "lineitem" else df).write.parquet(f"{tmp_path}/{t}.parquet")
    rules = lambda d: {r["rule"] for r in catalog.QUERIES["minimality_prune"](spark, d).collect()}
    assert "(net_c + sur_c) = due_c" not in rules(small) | rules(str(tmp_path))
    assert all(r["hits"] * 5 >= r["n_rows"] * 4 for r in catalog.QUERIES["minimality_prune"](spark, str(tmp_path)).collect())
