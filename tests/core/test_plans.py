"""Plans: what reaches the scan, how often rows move, what stays out of Python."""

import re

import pytest
from attrition import catalogue
from attrition.operators import contact_graph as G
from attrition.operators import ranks as R
from attrition.operators import structure as N
from attrition.operators import usage as U
from attrition.sources.tables import contact, read_table, session, subscriber
from pyspark.sql import functions as F

QUERIES = catalogue.queries()


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark, sf):
    orders = read_table(spark, sf, "orders").where(F.col("o_orderdate") >= F.lit("2001-01-01").cast("timestamp_ntz")).select("o_custkey")
    text = plan(orders)
    assert "GreaterThanOrEqual(o_orderdate" in text
    assert set(re.findall(r"(\w+):", re.search(r"ReadSchema: struct<([^>]*)>", text)[1])) == {"o_custkey", "o_orderdate"}
    assert "p_retailprice" not in plan(QUERIES["handset"](spark, sf))


@pytest.mark.parametrize("name", ["usage_month", "usage_multi", "feature_table", "arcs", "best_similarity", "local_clustering", "all_ranks", "peer_share", "join_as_of", "join_range", "windows", "auc", "split_gain"])
def test_no_python_and_no_product(name, spark, sf):
    text = plan(QUERIES[name](spark, sf))
    assert not re.search(r"Python|Pandas|MapInArrow|CartesianProduct", text)


def test_a_rank_round_moves_rows_for_one_join_and_one_sum(spark, sf):
    arcs = G.build_arcs(contact(spark, sf))
    nodes = G.build_nodes(arcs)
    count = lambda n: plan(R.receive_rank(nodes, arcs, "n_events", rounds=n)).count("Exchange hashpartitioning(taker")
    assert count(3) - count(2) == 1


def test_daily_weekly_and_monthly_sums_read_once(spark, sf):
    assert plan(U.multi_unit_rollup(contact(spark, sf))).count("FileScan parquet") == 2  # lines and orders


def test_windows_over_scores_go_range_by_range(spark, sf):
    for name in ("auc", "roc"):
        keys = re.findall(r"windowspecdefinition\((\w+)#", plan(QUERIES[name](spark, sf)))
        assert keys and set(keys) == {"_range"}, name


def test_rounds_do_not_move_arcs_again(spark, sf):
    arcs = G.build_arcs(contact(spark, sf))
    text = plan(R.receive_rank(G.build_nodes(arcs), arcs, "n_events", rounds=3))
    assert "Bucketed: true" in text and not re.search(r"Window", text)
    moved = [x for x in re.findall(r"Exchange hashpartitioning\(giver[^\n]*\n[^\n]*\n[^\n]*", text) if "moves" in x]
    assert not moved


def test_sides_are_cut_before_blocks(spark, sf):
    from attrition.operators import similarity as S

    arcs = G.build_arcs(contact(spark, sf))
    nodes = G.build_nodes(arcs, subscriber(spark, sf))
    text = plan(S.home_couples(N.friends(arcs), nodes))
    assert text.index("Generate explode(sequence") < text.index("max(_l"), "lower in the plan: blocks are made of marked rows"


def test_samples_do_not_order_a_class(spark):
    from attrition.operators import resample as B

    rows = spark.range(5000).selectExpr("id AS sub_id", "CAST(id % 10 = 0 AS INT) AS label")
    for fn in (B.undersample, B.oversample):
        assert not re.search(r"windowspecdefinition\(label#\d+, _draw", plan(fn(rows)))


def test_directories_are_sent_to_tasks(spark, sf):
    assert "BroadcastHashJoin" in plan(subscriber(spark, sf)) and "BroadcastHashJoin" in plan(U.place(session(spark, sf), read_table(spark, sf, "supplier").select(F.col("s_suppkey").alias("site"), "s_name")))


def test_triangles_start_from_the_smaller_degree(spark):
    star = N.friends(spark.createDataFrame([(0, i) for i in range(1, 300)], "src BIGINT, dst BIGINT"))
    assert N.triangles(star).count() == 0
