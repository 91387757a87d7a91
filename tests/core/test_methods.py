"""Thresholds, balancing, leakage, measures and learners."""

import math
import random

import numpy as np
import pytest
from attrition.functions.periods import BASELINE, months_before
from attrition.operators import learners as LR
from attrition.operators import measures as M
from attrition.operators import outcome as O
from attrition.operators import profile as P
from attrition.operators import refine as R
from attrition.operators import resample as B
from attrition.operators import second_order as Q
from attrition.operators import usage as U
from attrition.plans import experiments as X
from attrition.sources import landing as L
from attrition.sources.tables import contact
from pyspark.sql import functions as F


def table(spark, columns, n=100):
    names = list(columns)
    return spark.createDataFrame([(i, *[columns[c](i) for c in names]) for i in range(n)], "sub_id BIGINT, " + ", ".join(f"{c} {'STRING' if c.startswith('t_') else 'DOUBLE'}" for c in names))


def test_missing_thresholds_are_strict(spark):
    df = table(spark, {"seventy": lambda i: None if i < 70 else 1.0 * i, "more": lambda i: None if i < 71 else 1.0 * i, "full": float})
    assert R.sparse_columns(df, ("sub_id",)) == ["more"]
    wide = spark.createDataFrame([(k, *[None if c < k else 1.0 for c in range(10)]) for k in (0, 5, 9, 10)], "sub_id BIGINT, " + ", ".join(f"c{i} DOUBLE" for i in range(10)))
    assert sorted(r[0] for r in R.drop_sparse_rows(wide, ("sub_id",)).collect()) == [0, 5, 9]


def test_categories_ties_and_limits(spark):
    df = table(spark, {"t_c": lambda i: None if i % 100 == 99 else f"v{i % 40:02d}"}, 400)
    kept = R.top_categories(df, "t_c")
    assert len(kept) == 31 and kept == sorted(kept, key=lambda v: (-sum(f"v{i % 40:02d}" == v and i % 100 != 99 for i in range(400)), v))
    out = R.keep_categories(R.fill_category(df, ["t_c"]), {"t_c": [*kept, R.OTHER]})
    assert out.select("t_c").distinct().count() == 32


def test_duplicates_need_equal_nulls(spark):
    df = table(spark, {"a": float, "b": float, "c": lambda i: None if i == 3 else float(i), "d": lambda i: None if i == 3 else float(i)})
    assert R.duplicates(df, "sub_id") == ["b", "d"]


def test_correlation(spark):
    df = table(spark, {"x": float, "twice": lambda i: 2.0 * i, "minus": lambda i: -1.0 * i, "noise": lambda i: float(i * 7919 % 101), "same": lambda i: 3.0})
    r = {(a["left_col"], a["right_col"]): a["r"] for a in R.pearson(df, ["x", "twice", "minus", "noise", "same"]).collect()}
    assert r["x", "twice"] == pytest.approx(1) and r["x", "minus"] == pytest.approx(-1) and abs(r["x", "noise"]) < 0.3 and r["x", "same"] is None
    assert R.correlated(df, ["x", "twice", "minus", "noise", "same"]) == ["twice", "minus"]


def test_refiner_is_replayed_and_leaves_no_gaps(spark):
    df = table(spark, {"a": lambda i: None if i % 3 == 0 else float(i), "same": lambda i: 1.0, "few": lambda i: float(i % 2), "t_k": lambda i: None if i % 5 == 0 else f"k{i % 4}", "gone": lambda i: None if i % 10 else float(i)}).withColumn("label", F.lit(0))
    model = R.Refiner().fit(df)
    out = model.transform(df)
    assert set(out.columns) == {"sub_id", "a", "t_k", "label"} and model.report["before"] == 7 and model.report["after"] == 4
    assert out.where("a IS NULL OR t_k IS NULL").count() == 0
    assert sorted(map(tuple, model.transform(df).collect())) == sorted(map(tuple, out.collect()))
    assert R.Refiner(few="as_category").fit(df).transform(df).schema["few"].dataType.simpleString() == "string"
    assert "a" not in R.Refiner(any_null=True).fit(df).transform(df).columns


def test_balancing_sizes(spark):
    df = spark.createDataFrame([(i, int(i < 6)) for i in range(100)], "sub_id BIGINT, label INT")
    size = lambda x: {r["label"]: r["rows"] for r in B.balance_report(x).collect()}
    assert size(B.undersample(df)) == {0: 6, 1: 6} and size(B.oversample(df)) == {0: 94, 1: 94}
    assert P.class_share(df).first()["unbalanced"]
    assert {round(r["w"], 6) for r in B.weighted(df).groupBy("label").agg(F.sum("weight").alias("w")).collect()} == {94.0}
    # 70 in a hundred of 300 000 and of 4 700 000, evened out
    assert 2 * (300_000 * 70 // 100) == 420_000
    parts = B.folds(B.split(df), 10)
    assert parts.count() == 100 and parts.select("fold").distinct().count() == 10


def test_no_feature_sees_what_follows_the_baseline(spark, sf):
    c = contact(spark, sf)
    base = "1999-08-01"
    cut = c.where(F.col("ts") < F.lit(base).cast("timestamp_ntz"))
    for fn in (lambda x: U.history(x, 6, base), lambda x: U.idle_days(x, base), lambda x: U.category_counts(x, baseline=base), lambda x: U.period_rollup(x, "month", base)):
        assert sorted(map(str, fn(c).collect())) == sorted(map(str, fn(cut).collect()))
    assert months_before(BASELINE, 4) == "2001-04-01" and months_before("2001-02-01", 3) == "2000-11-01"


def test_gap_moves_the_label(spark):
    people = spark.createDataFrame([(1,), (2,)], "sub_id BIGINT")
    acts = spark.createDataFrame([(1, "2001-01-15"), (2, "2001-03-15")], "sub_id BIGINT, ts STRING").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    label = lambda gap: {r[0]: r[1] for r in O.idle_label(acts, people, "2001-01-01", 2, gap).collect()}
    assert label(0) == {1: 0, 2: 1} and label(2) == {1: 1, 2: 0}


def scored(spark, rows):
    return spark.createDataFrame([(i, y, s) for i, (y, s) in enumerate(rows)], "sub_id BIGINT, label INT, score DOUBLE")


def test_auc_and_roc(spark):
    from pyspark.ml.evaluation import BinaryClassificationEvaluator

    assert M.auc_value(scored(spark, [(0, 0.5), (1, 0.5)] * 10)) == 0.5
    assert M.auc_value(scored(spark, [(0, 0.1), (1, 0.9)] * 10)) == 1.0
    assert M.auc(scored(spark, [(0, 0.1), (1, 0.9)])).first()[0] == 1 - M.auc(scored(spark, [(1, 0.1), (0, 0.9)])).first()[0]
    rng = random.Random(4)
    df = scored(spark, [(int(rng.random() < 0.3), round(rng.random(), 1)) for _ in range(300)])
    auc = M.auc_value(df)
    assert auc == pytest.approx(BinaryClassificationEvaluator(rawPredictionCol="score", numBins=0).evaluate(df))
    points = sorted((r["fpr"], r["tpr"]) for r in M.roc(df).collect())
    assert points[0] == (0, 0) and points[-1] == (1, 1)
    assert auc == pytest.approx(sum((x2 - x1) * (y1 + y2) / 2 for (x1, y1), (x2, y2) in zip(points, points[1:])))
    assert M.needs_retrain(0.3, 0.9, 0.9) and M.needs_retrain(0.0, 0.9, 0.8) and not M.needs_retrain(0.1, 0.9, 0.89)


def test_one_level_equals_numpy(spark):
    rng = np.random.default_rng(0)
    x, y = rng.integers(0, 8, 400), rng.random(400) < 0.4
    missing = rng.random(400) < 0.2
    b = np.where(missing, -1, x)
    g, h = 0.5 - y, np.full(400, 0.25)
    hist = spark.createDataFrame([(0, 0, int(k), float(g[b == k].sum()), float(h[b == k].sum())) for k in range(-1, 8)], "node BIGINT, feature INT, bin INT, g DOUBLE, h DOUBLE")
    best = 0.0
    for cut in range(8):
        for left_too in (False, True):
            left = (b <= cut) & (b >= 0) | ((b == -1) & left_too)
            if left.any() and (~left).any():
                best = max(best, Q.gain_of(g[left].sum(), h[left].sum(), g[~left].sum(), h[~left].sum(), 1.0, 0.0))
    assert Q.best_splits(hist).first()["gain"] == pytest.approx(best)


@pytest.fixture(scope="module")
def xor(spark):
    rng = random.Random(1)
    rows = []
    for i in range(600):
        a, b, c = rng.random(), rng.random(), rng.random()
        rows.append((i, int((a > 0.5) != (b > 0.5)), None if rng.random() < 0.1 else a, b, c))
    return spark.createDataFrame(rows, "sub_id BIGINT, label INT, a DOUBLE, b DOUBLE, c DOUBLE").cache()


def test_booster_learns_an_interaction_and_tells_its_features(spark, xor):
    trace = []
    model = Q.boosted_second(xor, ["a", "b", "c"], trees=9, depth=3, eta=0.5, trace=trace)
    assert all(t >= 0 for t in trace) and len(model.trees) == 9
    assert M.auc_value(model.score(xor, ["sub_id", "label"])) > 0.93
    gain = {r["feature"]: r["gain"] for r in model.importance(spark).collect()}
    assert min(gain["a"], gain["b"]) > gain["c"]
    leaves = model.table(spark).where("feature IS NULL").groupBy("tree").count().collect()
    assert len(leaves) == 9 and max(r["count"] for r in leaves) <= 8
    capped = Q.own_tree(xor, ["a", "b", "c"], depth=6, max_nodes=10)
    assert capped.table(spark).count() == 9 and capped.table(spark).where("feature IS NULL").count() == 5, "a split adds two nodes"


@pytest.mark.parametrize("name", ["decision_tree", "random_forest", "boosted_first"])
def test_library_learners(spark, xor, name):
    model = LR.LEARNERS[name](xor, ["a", "b", "c"], **LR.SMALL[name])
    assert M.auc_value(model.score(xor)) > 0.8 and model.importance(spark).count() == 3


def test_cross_validation_uses_every_fold_once(spark, xor):
    got = LR.cross_validate(xor, ["a", "b", "c"], "decision_tree", [{"depth": 1}, {"depth": 5}], k=3, balance="undersample").collect()
    assert len(got) == 6 and {r["fold"] for r in got} == {0, 1, 2}


def test_switched_lines_are_tracked(spark, sf):
    rows = X.run("w11", spark, sf).where("id >= 0").collect()
    assert {r["week"] for r in rows} <= set(range(7, 15)) and all(0 < r["max_cos_rival"] <= 1.000001 for r in rows)
    assert sum(r["week"] >= 11 for r in rows) > sum(r["week"] < 11 for r in rows) > 0  # second lines take up more friends each week


def test_switched_lines_come_from_the_contacts(spark, sf):
    contact, nodes = X.switched_lines(spark, sf)
    assert contact.where("src < 0").count() > 0 and any("lineitem" in f for f in contact.inputFiles())
    assert nodes.groupBy("operator").count().select("count").distinct().count() == 1


def test_import_slices_cover_all(spark):
    df = spark.range(0, 103).withColumnRenamed("id", "k").union(spark.sql("SELECT CAST(NULL AS BIGINT)"))
    parts = [df.where(p).count() for p in L.range_slices(0, 102, "k", 4)]
    assert sum(parts) == 104 and max(parts) - min(parts) <= 2


def test_bad_rows_and_formats(spark, tmp_path):
    (tmp_path / "x.csv").write_text("a,b\n1,2\nx,3\n4\n")
    read = lambda mode: spark.read.schema("a INT, b INT, _corrupt_record STRING").option("header", True).option("mode", mode).csv(str(tmp_path))
    assert read("PERMISSIVE").count() == 3 and len(read("DROPMALFORMED").select("a", "b").collect()) == 1
    xml = spark.createDataFrame([("<r><k>5</k></r>",), ("<r/>",)], "t STRING")
    assert [r["k"] for r in L.parse(xml, "t", "k INT", "xml").select("parsed.k").collect()] == [5, None]
    trial = {(r["fmt"], r["codec"]): r for r in L.storage_trial(spark.range(20000).selectExpr("id", "id % 7 AS g"), "id", "g").collect()}
    assert trial["parquet", "snappy"]["bytes"] < trial["csv", "none"]["bytes"] and trial["avro", "snappy"]["status"] in ("unavailable", "measured")
    L.store(spark.range(50).selectExpr("id", "id % 3 AS p"), str(tmp_path / "s"), "p", "id")
    assert spark.read.parquet(str(tmp_path / "s")).where("p = 1").count() == 17


def test_near_pairs_are_near_and_exact_search_is_exact(spark):
    from attrition.operators import relational as X

    rng = np.random.default_rng(3)
    v = rng.normal(size=(60, 8))
    v[30:] = v[:30] + rng.normal(scale=0.05, size=(30, 8))
    rows = spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(v)], "vec_id BIGINT, embedding ARRAY<FLOAT>")
    got = {(r["a"], r["b"]) for r in X.near_pairs(rows, 0.8, length=2.0).collect()}
    assert all(np.linalg.norm(v[a] - v[b]) < 0.81 for a, b in got) and len(got & {(i, i + 30) for i in range(30)}) > 24
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    near = X.nearest(rows.where("vec_id < 5"), rows, 3).collect()
    for q in range(5):
        want = [i for i in np.argsort(-(unit @ unit[q])) if i != q][:3]
        assert sorted(r["vec_id"] for r in near if r["query"] == q) == sorted(want)


@pytest.mark.parametrize("block", [7, 16_384])
def test_near_pairs_come_once_from_blocks_of_a_bucket(spark, block):
    from attrition.operators import relational as X

    rng = np.random.default_rng(4)
    v = rng.normal(scale=0.01, size=(50, 4)).astype(np.float32).astype(float) + 100.1  # one bucket in each table
    rows = spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(v)], "vec_id BIGINT, embedding ARRAY<DOUBLE>")
    got = sorted(tuple(r) for r in X.near_pairs(rows, 0.02, length=50.0, block=block).collect())
    want = sorted((i, j, float(np.linalg.norm(v[i] - v[j]))) for i in range(50) for j in range(i + 1, 50) if np.linalg.norm(v[i] - v[j]) < 0.02)
    assert [r[:2] for r in got] == [r[:2] for r in want] and np.allclose([r[2] for r in got], [r[2] for r in want])


def test_salted_join_refuses_to_repeat_unmatched_rows(spark):
    from attrition.operators import relational as X

    big, small = spark.createDataFrame([(1, i) for i in range(50)] + [(2, 0)], "k BIGINT, v BIGINT"), spark.createDataFrame([(1, "a"), (3, "c")], "k BIGINT, w STRING")
    for how in ("inner", "left", "left_semi", "left_anti"):
        assert sorted(map(str, X.salted_join(big, small, "k", how=how).collect())) == sorted(map(str, big.join(small, "k", how).collect()))
    with pytest.raises(ValueError):
        X.salted_join(big, small, "k", how="right")


def test_vectors_indexes_and_components(spark):
    df = table(spark, {"a": float, "b": lambda i: float(i % 7), "t_k": lambda i: f"k{i % 3}"}).withColumn("label", F.lit(1))
    out = R.assemble(df, seen=df.where("sub_id < 50"))
    assert out.first()["features"].size == 3
    assert R.pca(out, 2).first()["components"].size == 2


def test_long_and_wide_forms_return_what_they_were_given(spark):
    df = table(spark, {"a": lambda i: None if i % 2 else float(i), "b": float}, 10)
    back = U.to_wide(U.to_long(df), ["a", "b"])
    assert sorted(map(str, back.collect())) == sorted(map(str, df.collect()))


def test_bucketed_tables_join_without_moving(spark, tmp_path):
    df = spark.range(100).selectExpr("id AS sub_id", "id * 2 AS v")
    for name in ("left_b", "right_b"):
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        L.bucketed(df, name, "sub_id", 4)
    joined = spark.table("left_b").hint("merge").join(spark.table("right_b"), "sub_id")
    assert "Exchange" not in joined._jdf.queryExecution().sparkPlan().toString() and joined.count() == 100
    for name in ("left_b", "right_b"):
        spark.sql(f"DROP TABLE {name}")


def test_vector_labels_are_at_the_limit_of_balance(spark):
    """A stand-in for many dense features; held out, the given vectors tell their class hardly better than chance."""
    train, test, features = X.vector_task(spark, "/root/testdata/sf0.01")
    rows = train.union(test)
    assert len(features) == 64 and rows.count() == 500 and 0.05 < rows.agg(F.avg("label")).first()[0] < 0.15
    model = LR.decision_tree(train, features, depth=3)
    assert 0 <= M.auc_value(model.score(test)) <= 1 and model.importance(spark).count() == 64


def test_histories_and_tuning_cover_every_cell(spark, monkeypatch):
    monkeypatch.setattr(X, "planted_labels", lambda spark, d: spark.range(1))
    monkeypatch.setattr(X, "planted_task", lambda spark, d, **windows: (windows, None, dict.fromkeys(X.FAMILIES, [])))
    monkeypatch.setattr(X.LR, "evaluate", lambda train, *_: float(train["usage_months"]))
    for name in ("w3", "w4", "w5"):
        cells = {(r["months"], r["learner"]) for r in X.run(name, spark, "").collect()}
        assert cells == {(m, learner) for m in range(1, 10) for learner in X.FOUR}
    rows = spark.range(200).select(F.col("id").alias("sub_id"), (F.col("id") % 2).alias("label"))
    monkeypatch.setattr(X, "planted_task", lambda spark, d: (rows, None, {"both": []}))
    monkeypatch.setattr(X.LR, "evaluate", lambda *_: 0.5)
    got = X.run("w8", spark, "").groupBy("learner", "setting").agg(F.count_distinct("fold").alias("k")).collect()
    assert {r["k"] for r in got} == {10} and len(got) == sum(map(len, X.TUNING.values()))
    assert all(any(f"'{name}'" in r["setting"] for r in got) for name in ("depth", "max_nodes", "trees"))


def test_what_blocks_read_is_written_once(spark, sf):
    made = X.in_threads(range(4), lambda _: X.role(spark, sf, "contact"))
    assert all(m is made[0] for m in made)
    scans = X.usage_table(spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "l_orderkey" not in scans and "props" not in scans
    assert sorted(map(tuple, made[0].collect())) == sorted(map(tuple, contact(spark, sf).collect()))


def test_values_are_counted_twice_while_refining(spark, monkeypatch):
    calls, count = [], R.value_counts
    monkeypatch.setattr(R, "value_counts", lambda df, columns: calls.append(columns) or count(df, columns))
    rows = spark.createDataFrame([(i, i % 2, i, 1.0, float(i % 7), None if i < 90 else 1.0) for i in range(100)], "sub_id BIGINT, label INT, name BIGINT, one DOUBLE, seven DOUBLE, rare DOUBLE")
    model = R.Refiner().fit(rows)
    assert len(calls) == 2
    assert [model.dropped[k] for k in ("identifiers", "constants", "sparse")] == [["name"], ["one"], ["rare"]]


@pytest.mark.parametrize("least", [0.0, 3.0])
def test_cuts_found_by_tasks_equal_those_of_tables(spark, least):
    rng = np.random.default_rng(2)
    sums = {(n, f): np.where(rng.random(9) < 0.3, 0.0, [rng.normal(size=9), rng.random(9)]) for n in range(3) for f in range(5)}
    sums |= {(0, 5): sums[0, 2], (3, 0): np.zeros((2, 9))}  # equal cuts of two features; a node without a row
    packed = spark.createDataFrame([(n, f, bytearray(part.tobytes())) for (n, f), s in sums.items() for part in (s * 0.25, s * 0.75)], "node BIGINT, feature INT, sums BINARY")
    got = {}
    for r in sorted(Q.best_of(packed, 8, 1.0, 0.0, least).collect(), key=lambda r: (-(r["gain"] or -1e9), r["feature"] or 0)):
        if r["gain"] is not None:
            got.setdefault(r["node"], r)
        s = sums[r["node"], r["first"]]
        assert (r["G"], r["H"]) == pytest.approx((s[0].sum(), s[1].sum()))
    table = [(n, f, b - 1, float(s[0, b]), float(s[1, b])) for (n, f), s in sums.items() for b in range(9) if s[1, b]]
    want = {r["node"]: r for r in Q.best_splits(spark.createDataFrame(table, "node BIGINT, feature INT, bin INT, g DOUBLE, h DOUBLE"), min_child=least).collect()}
    assert got.keys() == want.keys()
    for n, r in want.items():
        assert all(got[n][c] == r[c] for c in ("feature", "bin", "default_left"))
        assert all(got[n][c] == pytest.approx(r[c]) for c in ("gain", "gl", "hl", "gr", "hr"))


def test_few_blocks_meet_in_one_job(spark, sf, monkeypatch):
    joins, keep = [], X.kept
    count = lambda df: str(df._jdf.queryExecution().optimizedPlan()).count("Join LeftOuter")
    monkeypatch.setattr(X, "kept", lambda df, name="table": joins.append((name, count(df))) or keep(df, name))
    got = X.usage_table(spark, sf)
    assert max(n for name, n in joins if name == "blocks") <= 2 * X.BLOCKS and sum(name == "blocks" for name, _ in joins) > 4
    people = X.population(spark, sf)
    assert got.count() == people.count() and {"n_out", "last_result", "rival_friend_share", "state"} <= set(got.columns)


def test_one_task_grows_the_trees_of_the_jobs_by_level(spark, monkeypatch):
    x = lambda i: F.when(F.pmod(F.xxhash64("sub_id", F.lit(i)), F.lit(9)) > 0, F.pmod(F.xxhash64("sub_id", F.lit(-i - 1)), F.lit(50)).cast("double"))
    rows = spark.range(0, 3000, 1, 3).withColumnRenamed("id", "sub_id").select("sub_id", *[x(i).alias(f"x{i}") for i in range(4)])
    rows = rows.withColumn("label", (F.coalesce("x0", F.lit(20.0)) + F.coalesce("x1", F.lit(0.0)) * F.coalesce("x2", F.lit(3.0)) > 500).cast("int"))
    names, options = [f"x{i}" for i in range(4)], {"trees": 10, "depth": 3, "col_share": 0.8}
    spark.sparkContext.setJobGroup("one task", "")
    try:
        one, gains = Q.boosted_second(rows, names, trace=(trace := []), **options), trace
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("one task")) <= 10, "not a job for each level"
    few = Q.own_tree(rows, names, depth=6, max_nodes=9)
    monkeypatch.setattr(Q, "IN_TASK", 0)
    every, capped = Q.boosted_second(rows, names, trace=(trace := []), **options), Q.own_tree(rows, names, depth=6, max_nodes=9)
    for a, b in ((one, every), (few, capped)):
        assert [sorted(t) for t in a.trees] == [sorted(t) for t in b.trees] and len(a.trees) == len(b.trees)
        for s, t in zip(a.trees, b.trees):
            for n in s:
                assert [s[n].get(k) for k in ("feature", "bin", "cut", "default_left")] == [t[n].get(k) for k in ("feature", "bin", "cut", "default_left")]
                assert math.isclose(s[n]["leaf"], t[n]["leaf"], rel_tol=1e-6, abs_tol=1e-9)
    assert len(few.trees[0]) == 9 and all(math.isclose(a, b, rel_tol=1e-6) for a, b in zip(gains, trace)) and len(gains) == len(trace) == 10
    empty = Q.boosted_second(rows.where("sub_id < 0"), names, trees=2, depth=2)
    monkeypatch.undo()
    assert Q.boosted_second(rows.where("sub_id < 0"), names, trees=2, depth=2).trees == empty.trees


def test_folds_are_balanced_and_binned_once_for_all_settings(spark, monkeypatch):
    rows = spark.range(600).withColumnRenamed("id", "sub_id").select("sub_id", (F.col("sub_id") % 7 == 0).cast("int").alias("label"), (F.col("sub_id") % 11).cast("double").alias("a"), (F.col("sub_id") % 14).cast("double").alias("b"))
    made, own = [], LR.balanced
    monkeypatch.setattr(LR, "balanced", lambda *a: made.append(a) or own(*a))
    grids = {"decision_tree": [{"depth": 2}, {"depth": 4}], "capped_tree": [{"depth": 4, "max_nodes": 9}, {"depth": 4, "max_nodes": 31}]}
    got = LR.cross_validate_all(rows, ["a", "b"], grids, k=3, balance="undersample").collect()
    assert len(made) == 3 and len({(r["learner"], r["setting"], r["fold"]) for r in got}) == len(got) == 12
    parts = B.folds(rows, 3)
    for r in got:
        name, options = r["learner"], next(s for s in grids[r["learner"]] if str(s) == r["setting"])
        want = LR.evaluate(parts.where(F.col("fold") != r["fold"]), parts.where(F.col("fold") == r["fold"]), ["a", "b"], name, options, "undersample")
        assert math.isclose(r["auc"], want, abs_tol=1e-9)


def test_auc_of_bins_is_that_of_the_running_sums(spark):
    rng = random.Random(5)
    scored = spark.createDataFrame([(rng.randint(0, 1), round(rng.random(), 3)) for _ in range(400)] + [(1, None), (0, None)], "label INT, score DOUBLE")
    for bins in (7, 100_000):
        assert math.isclose(M.auc_value(scored, bins), M.auc(scored, bins).first()[0], rel_tol=1e-12)
    assert M.auc_value(scored.where("label = 1"), 10) == 0.5


def test_windows_of_usage_make_no_graph_table(spark, sf, monkeypatch):
    monkeypatch.setattr(X, "graph_table", lambda *a, **k: pytest.fail("a graph table"))
    got = X.run("w3", spark, sf, months=(2,), learners=("decision_tree",)).collect()
    assert [(r["months"], r["family"], r["learner"]) for r in got] == [(2, "usage", "decision_tree")] and 0 <= got[0]["auc"] <= 1
