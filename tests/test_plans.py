"""The physical plans that the design counts on."""

from __future__ import annotations

import pytest

from pdpview.catalog import QUERIES
from pdpview.operators import derive, query, relational  # noqa: F401
from pdpview.plans import workloads as wl


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark, small):
    text = plan(QUERIES["scan_pruned"].run(spark, small))
    assert "GreaterThanOrEqual(o_orderdate" in text and "o_totalprice" not in text


def test_view_queries_read_the_view_alone(spark, tmp_path):
    path = str(tmp_path / "view")
    spark.range(100).selectExpr("id", "CAST(id % 10 AS INT) AS release_step", "id % 3 = 0 AS is_view").write.partitionBy("release_step").parquet(path)
    text = plan(query.answer(spark.read.parquet(path), 4))
    assert "orders" not in text and "PartitionFilters: [isnotnull(release_step" in text and text.count("Exchange") <= 1


def test_no_global_window_on_rows(spark, small):
    for name in ("w1w_pairs_truncated", "w2_pairs_truncated", "surrogate_rid"):
        text = plan(QUERIES[name].run(spark, small))
        for line in text.splitlines():
            if "SinglePartition" in line:
                assert "sum" in text  # only the partition counts of the surrogate ids
                assert name == "surrogate_rid"


def test_derive_has_no_python(spark, small):
    assert "Python" not in plan(QUERIES["w1w_pairs_truncated"].run(spark, small)) and "Pandas" not in plan(QUERIES["interval_release"].run(spark, small))


def test_pairs_are_joined_by_key_and_step(spark, small):
    for name in ("w2_truth_by_step", "w1w_truth_by_step"):
        joins = [x for x in plan(QUERIES[name].run(spark, small)).splitlines() if "Join" in x]
        assert joins and all("near" in x for x in joins)


def test_numbering_splits_a_step(spark, small):
    text = plan(derive.numbered(derive.derive(wl.W1W, *wl.sides(wl.W1W, spark, small))))
    assert "hashpartitioning(born_step" in text and all("__part" in x for x in text.splitlines() if "row_number" in x and "Window" in x and "born_step" in x and "l_rid" in x and "ord" not in x and "__i" in x)


@pytest.mark.parametrize("name", ["joint_noise", "agg_noise_stats", "fn_maps", "geometric_noise", "join_cross", "joint_noise_three_servers", "udf_noise"])
def test_noise_and_surface_read_a_given_table(spark, small, name):
    assert "FileScan parquet" in plan(QUERIES[name].run(spark, small)) and "orders.parquet" in plan(QUERIES[name].run(spark, small))
