"""Streams over the same rows equal their batch twins; late rows, restarts and alarms behave as stated."""

import pytest
from attrition.operators import contact_graph as G
from attrition.operators.second_order import boosted_second
from attrition.operators.learners import Fitted
from attrition.streaming import live
from pyspark.sql import functions as F


@pytest.fixture(scope="module")
def files(spark, sf, tmp_path_factory):
    """The events in three files, in order of time."""
    at = str(tmp_path_factory.mktemp("events"))
    e = spark.read.parquet(f"{sf}/events.parquet")
    third = e.count() // 3 + 1
    for i in range(3):
        e.where(F.floor(F.col("event_id") / third) == i).coalesce(1).write.mode("append").parquet(at)
    return at


def same(a, b):
    """Equal rows, sums to six digits: batches add in another order."""
    plain = lambda df: sorted(str(tuple(round(x, 6) if isinstance(x, float) else x for x in r)) for r in df.collect())
    return plain(a) == plain(b)


@pytest.mark.parametrize("fn", [live.live_usage, live.live_sliding], ids=["tumbling", "sliding"])
def test_complete_mode_equals_the_batch(fn, spark, sf, files, tmp_path):
    got = live.run_to_end(fn(live.event_stream(spark, files)), f"s_{fn.__name__}", "complete", str(tmp_path))
    assert same(got, fn(live.zoned(spark.read.parquet(f"{sf}/events.parquet"))))


def test_sessions_and_dedup_in_append_mode(spark, sf, files, tmp_path):
    batch = live.zoned(spark.read.parquet(f"{sf}/events.parquet"))
    got = live.run_to_end(live.live_sessions(live.event_stream(spark, files)), "sessions", "append", str(tmp_path / "a"))
    closed = {str(r) for r in got.collect()}
    assert closed and closed <= {str(r) for r in live.live_sessions(batch).collect()}
    twice = live.event_stream(spark, files).withColumn("n", F.explode(F.array(F.lit(1), F.lit(2)))).drop("n")
    assert live.run_to_end(live.live_once(twice), "once", "append", str(tmp_path / "b")).count() == batch.count()


def test_enrich_and_pairs(spark, sf, files, tmp_path):
    from attrition.sources.tables import subscriber

    batch = live.zoned(spark.read.parquet(f"{sf}/events.parquet"))
    got = live.run_to_end(live.live_enrich(live.event_stream(spark, files), subscriber(spark, sf)), "enriched", "append", str(tmp_path / "a"))
    assert same(got.select("event_id", "operator"), live.live_enrich(batch, subscriber(spark, sf)).select("event_id", "operator"))
    pairs = live.run_to_end(live.live_pairs(live.event_stream(spark, files), "12 hours", "1 day"), "pairs", "append", str(tmp_path / "b"))
    assert same(pairs, live.live_pairs(batch, "12 hours"))


def events(spark, rows):
    return spark.createDataFrame([(i, t, u, "view", 1.0, "{}") for i, (t, u) in enumerate(rows)], "event_id BIGINT, ts STRING, user_id BIGINT, event_type STRING, value DOUBLE, props STRING").withColumn("ts", F.col("ts").cast("timestamp_ntz"))


def test_late_rows_inside_the_watermark_count_and_outside_do_not(spark, tmp_path):
    src = str(tmp_path / "in")
    for rows in ([("2024-01-01 10:00:00", 1)], [("2024-01-03 10:00:00", 1)], [("2024-01-03 10:01:00", 1)], [("2024-01-01 11:00:00", 1), ("2024-01-03 09:30:00", 1)], [("2024-01-09 00:00:00", 1)]):
        events(spark, rows).coalesce(1).write.mode("append").parquet(src)
    got = live.run_to_end(live.live_usage(live.event_stream(spark, src)), "late", "append", str(tmp_path / "c")).collect()
    # the row inside the watermark counts, the one outside came too late; the last window is still open
    assert sorted((str(r["start"].date()), r["n"]) for r in got) == [("2024-01-01", 1), ("2024-01-03", 3)]


def test_idle_alarm(spark, tmp_path):
    src = str(tmp_path / "in")
    for rows in ([("2024-01-01 00:00:00", 1), ("2024-01-01 00:00:00", 2)], [("2024-01-03 00:00:00", 2)], [("2024-01-06 12:00:00", 2)], [("2024-01-07 00:00:00", 2)]):
        events(spark, rows).coalesce(1).write.mode("append").parquet(src)
    got = live.run_to_end(live.live_idle(live.event_stream(spark, src), days=3), "idle", "append", str(tmp_path / "c")).collect()
    alarms = {(r["user_id"], str(r["last_seen"].date())) for r in got if r["alarm"]}
    assert (1, "2024-01-01") in alarms and all(u == 1 or d == "2024-01-03" for u, d in alarms)


def test_arcs_are_kept_up_and_equal_the_batch(spark, sf, tmp_path):
    from attrition.sources.tables import contact

    rows = contact(spark, sf).select("src", "dst", "duration", "kind", "ts")
    rows.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    for _ in range(2):  # the second run finds nothing new
        live.live_arcs(stream, str(tmp_path / "arcs"), str(tmp_path / "c")).awaitTermination()
    want = G.build_arcs(rows, months=None, baseline="2100-01-01")
    assert same(live.merged_arcs(spark, str(tmp_path / "arcs")), want)


def test_scoring_a_stream(spark, tmp_path):
    rows = spark.range(200).selectExpr("id AS sub_id", "CAST(id % 2 AS INT) AS label", "CAST(id % 2 AS DOUBLE) + id / 1000 AS x")
    model = Fitted("boosted_second", ["x"], boosted_second(rows, ["x"], trees=2, depth=2))
    rows.write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(rows.schema).parquet(str(tmp_path / "in"))
    got = live.run_to_end(live.live_score(stream, model, ["sub_id", "label"]), "live_scores", "append", str(tmp_path / "c"))
    assert same(got, model.score(rows))


def test_appended_rows_lie_in_files_not_on_the_driver(spark, files, tmp_path):
    got = live.run_to_end(live.event_stream(spark, files), "in_files", "append", str(tmp_path / "c"))
    assert got.inputFiles() and got.count() == spark.read.parquet(files).count()
    (tmp_path / "none").mkdir()
    assert live.run_to_end(live.event_stream(spark, str(tmp_path / "none")), "no_files", "append", str(tmp_path / "d")).count() == 0


def test_copies_with_higher_ids_do_not_come_late_and_batches_stay_small(spark, tmp_path):
    """Ids in another order than times: each id still counts once, whatever file it would have come in."""
    from attrition.plans import relational_queries as Q

    rows = [(f"2024-01-{day:02d} {hour:02d}:00:00", hour) for _ in range(3) for day in range(1, 11) for hour in range(4)]
    e = events(spark, rows)  # three times the same ten days, with higher ids each
    got = Q._streamed(spark, e.union(e.where("event_id % 3 = 0")), live.live_once, "append", batch=20)
    assert sorted(r["event_id"] for r in got.collect()) == list(range(120))
