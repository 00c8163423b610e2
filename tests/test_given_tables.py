"""Queries that made their rows up, or looked at a schema only, take them from the given tables."""

import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from relanom import registry, rules


@pytest.mark.parametrize("name", ["avg_rank_printed", "cost_parameters", "iforest_c", "recursive_tree", "rule_canonical", "rule_leaf_filter", "rule_paths", "theta_table"])
def test_without_tables_there_is_no_result(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        registry.queries()[name](spark, str(tmp_path)).collect()


def test_columns_without_a_value_are_no_features(spark, tmp_path):
    row = "1L AS o_orderkey, 1L AS o_custkey, current_date() AS o_orderdate, 'F' AS o_orderstatus, cast(null AS double) AS o_totalprice"
    spark.sql(f"SELECT {row}").write.parquet(str(tmp_path / "orders.parquet"))
    assert [r.name for r in registry.queries()["flat_admissible"](spark, str(tmp_path)).collect()] == ["o_orderstatus"]


def test_admitted_predicates_run_on_the_rows(spark, monkeypatch):
    monkeypatch.setattr(rules, "executable", lambda view, texts: texts[1:])
    found = registry.queries()["rule_rejections"](spark, "/root/testdata/sf0.001").filter("reason = 'fails'").collect()
    assert [r.text for r in found] == ["bought <= 3.0"]


def test_the_tree_is_walked_to_its_last_level(spark, tmp_path):
    spark.conf.set("spark.sql.cteRecursionRowLimit", "1000")
    spark.range(1, 5001).select(F.col("id").alias("c_custkey")).write.parquet(str(tmp_path / "customer.parquet"))
    found = {r.depth: (r.n, r.s) for r in registry.queries()["recursive_tree"](spark, str(tmp_path)).collect()}
    level = lambda d: range(2**d, min(2 ** (d + 1), 5001))
    assert found == {d: (len(level(d)), sum(level(d))) for d in range(13)}
