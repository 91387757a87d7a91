"""The toy graph with values worked out beforehand, invariants, and numpy as the reference."""

import math

import numpy as np
import pytest
from attrition.operators import contact_graph as G
from attrition.operators import ranks as R
from attrition.operators import similarity as S
from attrition.operators import structure as N

ARCS = [("A", "B", 3), ("A", "C", 1), ("B", "C", 2), ("C", "A", 2), ("C", "D", 2), ("D", "B", 1), ("D", "F", 1), ("E", "C", 4)]
NAMES = "ABCDEF"
#: Worked out by hand and by matrix products, to six digits.
RANKS = {
    ("receive", None, 1): (0.575, 1.2125, 2.0625, 0.575, 0.15, 0.575),
    ("receive", None, 2): (1.026562, 0.760937, 1.430312, 1.026562, 0.15, 0.394375),
    ("receive", None, 80): (0.612569, 0.800854, 1.088397, 0.612569, 0.15, 0.410342),
    ("send", "in", 1): (0.908929, 0.392857, 1.85, 1.2125, 0.635714, 0.15),
    ("send", "in", 2): (0.625089, 0.599286, 1.953214, 0.360982, 1.048571, 0.15),
    ("send", "in", 80): (0.483741, 0.359333, 0.86196, 0.353858, 0.568666, 0.15),
    ("send", "printed", 1): (1.6375, 0.575, 1.425, 0.575, 1.0, 0.15),
    ("send", "printed", 80): (1.02513, 0.535285, 0.906552, 0.377496, 0.920569, 0.15),
}
JACCARD = {"AB": 0.25, "AC": 0.2, "AD": 2 / 3, "AE": 0.5, "BC": 0.4, "BD": 0.2, "BE": 1 / 3, "BF": 1 / 3, "CD": 1 / 6, "CF": 0.25, "DE": 1 / 3}
COSINE = {"AB": 0.408248, "AC": 0.353553, "AD": 0.816497, "AE": 0.707107, "BC": 0.57735, "BD": 0.333333, "BE": 0.57735, "BF": 0.57735, "CD": 0.288675, "CF": 0.5, "DE": 0.57735}


@pytest.fixture(scope="module")
def toy(spark):
    rows = [(ord(a), ord(b), w, float(w)) for a, b, w in ARCS]
    return spark.createDataFrame(rows, "src BIGINT, dst BIGINT, n_events BIGINT, talk DOUBLE").cache()


@pytest.fixture(scope="module")
def pairs(toy):
    return N.friends(toy).cache()


def values(df, column):
    return {chr(r["id"]): r[column] for r in df.collect()}


@pytest.mark.parametrize("case", [c for c in RANKS if c[2] < 10])
def test_toy_ranks(toy, case):
    direction, norm, rounds = case
    fn = R.receive_rank if direction == "receive" else R.send_rank
    got = values(fn(G.build_nodes(toy), toy, "n_events", rounds=rounds, **({"norm": norm} if norm else {})), "rank")
    assert all(abs(got[n] - v) < 2e-6 for n, v in zip(NAMES, RANKS[case]))


@pytest.mark.parametrize("case", [c for c in RANKS if c[2] == 80])
def test_toy_ranks_converged(toy, case):
    direction, norm, _ = case
    fn = R.receive_rank if direction == "receive" else R.send_rank
    got = values(fn(G.build_nodes(toy), toy, "n_events", rounds=45, tol=1e-7, check_every=15, **({"norm": norm} if norm else {})), "rank")
    assert all(abs(got[n] - v) < 1e-3 for n, v in zip(NAMES, RANKS[case]))


def test_rank_invariants(toy):
    nodes = G.build_nodes(toy)
    total = lambda **o: sum(values(R.receive_rank(nodes, toy, "n_events", rounds=4, **o), "rank").values())
    assert abs(total(sinks="spread") - 6) < 1e-9 and abs(total(sinks="self") - 6) < 1e-9
    assert abs(total(teleport="share", sinks="spread") - 1) < 1e-9
    assert total() < 6
    assert all(abs(v - 1) < 1e-9 for v in values(R.receive_rank(nodes, toy, "n_events", d=0.0, rounds=2), "rank").values())
    ten = toy.selectExpr("src", "dst", "n_events * 10 AS n_events", "talk")
    a, b = (values(R.send_rank(nodes, t, "n_events", rounds=3), "rank") for t in (toy, ten))
    assert all(abs(a[n] - b[n]) < 1e-12 for n in a)
    back = toy.selectExpr("dst AS src", "src AS dst", "n_events", "talk")
    c = values(R.receive_rank(nodes, back, "n_events", rounds=3), "rank")
    assert all(abs(a[n] - c[n]) < 1e-12 for n in a)
    changes = [r["change"] for r in R.rank_trace(nodes, toy, "n_events", rounds=5).orderBy("round").collect()]
    assert all(y < x for x, y in zip(changes, changes[1:]))


def test_toy_structure(toy, pairs):
    assert values(N.neighbour_connectivity(pairs), "value") == pytest.approx({"A": 3.5, "B": 3.0, "C": 2.25, "D": 8 / 3, "E": 4.0, "F": 3.0})
    want = {"A": 1.0, "B": 2 / 3, "C": 1 / 3, "D": 1 / 3, "E": None, "F": None}
    for orient in (True, False):
        got = values(N.local_clustering(pairs, orient), "value")
        assert all(got[n] == (None if v is None else pytest.approx(v)) for n, v in want.items())
    got = {chr(r["id"]): (r["in_deg"], r["out_deg"]) for r in N.degrees(toy).collect()}
    assert got == {"A": (1, 2), "B": (2, 1), "C": (3, 2), "D": (1, 2), "E": (0, 1), "F": (1, 0)}


@pytest.mark.parametrize("block", [1000, 2])
def test_toy_similarity(pairs, block):
    got = {chr(r["a"]) + chr(r["b"]): r for r in S.similar_pairs(pairs, block=block).collect()}
    assert set(got) == set(JACCARD)
    assert all(abs(got[c]["jaccard"] - v) < 1e-9 for c, v in JACCARD.items()) and all(abs(got[c]["cosine"] - v) < 1e-6 for c, v in COSINE.items())


def test_hub_blocks_equal_the_plain_join(spark):
    star = spark.createDataFrame([(0, i) for i in range(1, 201)], "src BIGINT, dst BIGINT")
    a, b = (sorted(map(tuple, S.mutual_friends(N.friends(star), block=n).collect())) for n in (1000, 7))
    assert a == b and len(a) == 200 * 199 // 2


def graph(spark, edges):
    return N.friends(spark.createDataFrame(edges, "src BIGINT, dst BIGINT"))


def test_closed_forms(spark):
    full = graph(spark, [(i, j) for i in range(5) for j in range(i)])
    assert {r["value"] for r in N.local_clustering(full).collect()} == {1.0}
    path = graph(spark, [(i, i + 1) for i in range(4)])
    assert [r["bet"] for r in N.betweenness(path).orderBy("id").collect()] == [0, 3, 4, 3, 0]
    star = graph(spark, [(0, i) for i in range(1, 6)])
    got = {r["id"]: r["bet"] for r in N.betweenness(star).collect()}
    assert got[0] == 10 and set(list(got.values())[1:]) <= {0.0, 10.0} and sum(got.values()) == 10
    square = graph(spark, [(0, 1), (1, 2), (2, 3), (3, 0)])
    assert {r["bet"] for r in N.betweenness(square).collect()} == {0.5}
    assert {r["bet"] for r in N.betweenness(square, kind="count").collect()} == {1.0}
    every = {r["id"]: r["bet"] for r in N.betweenness(path, sources=1.1).collect()}
    assert every == {r["id"]: r["bet"] for r in N.betweenness(path).collect()}


def test_betweenness_counts_pairs_far_apart(spark):
    path = graph(spark, [(i, i + 1) for i in range(19)])
    for kind in ("share", "count"):
        assert [r["bet"] for r in N.betweenness(path, kind=kind).orderBy("id").collect()] == [i * (19 - i) for i in range(20)]


@pytest.mark.parametrize("options", [{}, {"kind": "count"}, {"sources": 0.4, "depth": 2}])
def test_betweenness_searches_without_rows_for_cells(spark, monkeypatch, options):
    rng = np.random.default_rng(5)
    edges = [(100 * c + int(a), 100 * c + int(b)) for c, n in enumerate((2, 9, 30, 60)) for a, b in rng.integers(0, n, (2 * n, 2))] + [(900, 901)]
    pairs, written = graph(spark, edges), []
    keep = N.kept
    monkeypatch.setattr(N, "kept", lambda df, name="table": written.append(name) or keep(df, name))
    monkeypatch.setattr(N, "AT_ONCE", 150)
    monkeypatch.setattr(N, "A_TASK", 4000)
    got = {r["id"]: r["bet"] for r in N.betweenness(pairs, **options).collect()}
    assert written == ["pairs", "betweenness"]
    monkeypatch.setattr(N, "MOST_PAIRS", 0)
    want = {r["id"]: r["bet"] for r in N.betweenness(pairs, **options).collect()}
    assert got.keys() == want.keys() and all(math.isclose(got[n], b, abs_tol=1e-9) for n, b in want.items()) and max(want.values()) > 10


@pytest.mark.parametrize("kind", ["share", "count"])
@pytest.mark.parametrize("levels", [60, 3])
def test_betweenness_of_sources_searched_together(spark, monkeypatch, kind, levels):
    rng = np.random.default_rng(6)
    edges = [(1000 * c + int(a), 1000 * c + int(b)) for c, n in enumerate((5, 90, 150)) for a, b in rng.integers(0, n, (2 * n, 2))] + [(5000 + i, 5001 + i) for i in range(50)]
    pairs = graph(spark, edges)
    packed = N.Packed.of(pairs, pairs.select("id").distinct())
    want, got, together = np.zeros(len(packed.ids)), np.zeros(len(packed.ids)), 0
    packed.search(packed.starts, kind, None, 0, want)
    monkeypatch.setattr(N, "LEVELS", levels)
    monkeypatch.setattr(N, "LINKS", 2000)
    for part in np.split(packed.starts, np.flatnonzero(np.diff(packed.low[packed.starts])) + 1):
        if packed.search_together(part, kind, 0, got):
            together += len(part)
        else:
            packed.search(part, kind, None, 0, got)
    assert np.allclose(got, want, rtol=1e-12, atol=1e-9) and want.max() > 100
    assert together == len(packed.starts) if levels == 60 else together < len(packed.starts) / 2
    monkeypatch.setattr(N, "DENSE", 10)
    all_ = {r["id"]: r["bet"] for r in N.betweenness(pairs, kind=kind).collect()}
    assert all(math.isclose(all_[i], w / 2, abs_tol=1e-9) for i, w in zip(packed.ids.tolist(), want.tolist()))


def test_against_numpy(spark, sf):
    from attrition.sources.tables import contact

    arcs = G.build_arcs(contact(spark, sf), months=9)
    rows = arcs.collect()
    ids = sorted({r["src"] for r in rows} | {r["dst"] for r in rows})
    at = {n: i for i, n in enumerate(ids)}
    w = np.zeros((len(ids), len(ids)))
    for r in rows:
        w[at[r["src"]], at[r["dst"]]] = r["n_events"]
    share = w / np.maximum(w.sum(axis=1, keepdims=True), 1e-300)
    x = np.ones(len(ids))
    for _ in range(6):
        x = 0.15 + 0.85 * (share.T @ x)
    got = {r["id"]: r["rank"] for r in R.receive_rank(G.build_nodes(arcs), arcs, "n_events", rounds=6).collect()}
    assert max(abs(got[n] - x[at[n]]) for n in ids) < 1e-9
    f = ((w + w.T) > 0).astype(float)
    common = f @ f
    pairs = {(r["a"], r["b"]): r["common"] for r in S.mutual_friends(N.friends(arcs)).collect()}
    assert all(common[at[a], at[b]] == c for (a, b), c in pairs.items()) and len(pairs) == int((np.triu(common, 1) > 0).sum())
    six = sum(v["value"] * d["deg"] * (d["deg"] - 1) for v, d in zip(N.local_clustering(N.friends(arcs)).orderBy("id").collect(), N.friend_counts(N.friends(arcs)).orderBy("id").collect()) if v["value"] is not None)
    assert math.isclose(six, np.trace(f @ f @ f), rel_tol=1e-9)
