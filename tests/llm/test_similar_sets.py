"""The shingle join against all pairs compared one by one."""

import itertools
import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from attrition.llm import similar_sets as S
from attrition.llm.common import words_of


def shingle_set(text):
    w = words_of(text)
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


def brute(rows):
    """{row's place: (size, smallest id in its component)} by comparing every pair."""
    sets = [shingle_set(t) for _, t in rows]
    parent = list(range(len(rows)))

    def top(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, j in itertools.combinations(range(len(rows)), 2):
        if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
            parent[top(i)] = top(j)
    least = {}
    for i, (k, _) in enumerate(rows):
        if k is not None:
            least[top(i)] = min(least.get(top(i), k), k)
    return sorted((str(k), len(s), str(least.get(top(i), k) if s else k)) for i, ((k, _), s) in enumerate(zip(rows, sets)))


def corpus(seed=3):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(300)]
    make = lambda n: [rng.choice(words) for _ in range(n)]
    common, rows, k = make(14), [], 0
    for n in (1, 2, 4, 5, 6, 9, 12, 20, 40, 80, 150, 400):
        base = make(n)
        for edits in (0, 0, 1, 1, 2, 3, 5):
            w = list(base)
            for _ in range(edits):
                w[rng.randrange(n)] = rng.choice(words)
            rows.append((k, " ".join(w).upper() if k % 2 else " ".join(w)))
            k += 1
    rows += [(k + i, " ".join(common + make(rng.randrange(3, 30)))) for i in range(60)]
    family = make(60)
    for i in range(90):  # one large family, whose members differ from one another more than from their source
        w = list(family)
        for _ in range(rng.randrange(4)):
            w[rng.randrange(60)] = rng.choice(words)
        rows.append((500 + i, " ".join(w)))
    rows += [(900, None), (901, ""), (902, " \n\t"), (None, rows[5][1]), (None, "alone in the world of words"), (5, rows[5][1]), (903, "of " * 3000), (904, "of " * 2500), (905, "A\x0bb\x0cc"), (906, "a b c"), (907, "a\x85b c")]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(k, t, 1) for k, t in corpus()], "doc_id long, text string, component_id int").repartition(5)


@pytest.mark.parametrize("way", ["plain", "small blocks", "frequent elements"])
def test_components_equal_all_pairs(docs, way, monkeypatch):
    if way == "small blocks":
        monkeypatch.setattr(S, "BLOCK", 7)
        monkeypatch.setattr(S, "LARGE", 5)
        monkeypatch.setattr(S, "CHUNK", 2000)
        monkeypatch.setattr(S, "PACK", 3000)
    if way == "frequent elements":
        monkeypatch.setattr(S, "FREQUENT", 2)
    got = sorted((str(r[0]), r[1], str(r[2])) for r in S.near_copies(docs).collect())
    assert got == brute(corpus())


def test_every_pair_within_the_bound_shares_a_signature():
    rng = np.random.default_rng(1)
    for frequent in (np.empty(0, dtype=np.uint64), np.sort(rng.integers(0, 40, 30).astype(np.uint64))):
        for size in [*range(1, 40), 60, 100, 333]:
            for _ in range(6):
                a = rng.choice(50 if size < 40 else 2000, size, replace=False).astype(np.uint64)
                common = rng.choice(a, min(size, int(np.ceil(size * 0.8)) + rng.integers(0, 2)), replace=False)
                b = np.unique(np.concatenate([common, rng.integers(5000, 9000, rng.integers(0, 1 + size // 5)).astype(np.uint64)]))
                a = np.unique(a)
                both = len(np.intersect1d(a, b))
                if 100 * both >= 80 * (len(a) + len(b) - both):
                    sig, own = S.signatures([a, b], frequent)
                    assert set(sig[own == 0].tolist()) & set(sig[own == 1].tolist()), (size, both, len(b))


def test_one_of_each_keeps_the_smallest_and_all_without_sets(docs):
    out = S.one_of_each(docs)
    assert out.columns == docs.columns
    kept = sorted(str(r["doc_id"]) for r in out.collect())
    want = {str(c) for k, n, c in brute(corpus()) if n and c == k} | {"900", "901", "902"}
    assert set(kept) == want and len(kept) == len(set(kept)) and "500" in kept


def test_empty(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert S.near_copies(empty).count() == 0 and S.one_of_each(empty).count() == 0


def test_near_copies_without_an_id(spark):
    words = [f"n{i}" for i in range(60)]
    near = " ".join([*words[:-1], "other"])
    docs = spark.createDataFrame([(1, " ".join(words)), (None, near), (None, "quite another text of seven words"), (2, "and one more of them here")], "doc_id long, text string")
    got = S.near_copies(docs).collect()
    size = len(shingle_set(near))
    assert sorted((str(r[0]), r[1], str(r[2])) for r in got) == brute([tuple(r) for r in docs.collect()])
    assert ("None", size, "1") in [(str(r[0]), r[1], str(r[2])) for r in got]


def test_sets_alike_without_a_link_are_not_dealt_out_to_one_another(spark, monkeypatch):
    rng, dealt, plain = random.Random(5), [], S.compared
    monkeypatch.setattr(S, "BLOCK", 4)
    monkeypatch.setattr(S, "LARGE", 5)
    monkeypatch.setattr(S, "compared", lambda rows: dealt.append(rows.count()) or plain(rows))
    base, rows = [f"c{i}" for i in range(120)], []
    for k in range(120):  # a third of each text's words of its own, in runs: similarity with any other about 0.5
        at = rng.randrange(90)
        rows.append((k, " ".join(base[:at] + [f"o{k}x{i}" for i in range(24)] + base[at + 24 :])))
    rows += [(500 + k, t + " end") for k, t in rows[:3]]
    got = sorted((str(r[0]), r[1], str(r[2])) for r in S.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == brute(rows)
    assert sum(dealt) < 3 * len(rows)


def test_written_tables_leave_no_shuffle_files(spark):
    from attrition.llm.common import saved

    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    files = lambda: {f for f in disk.getAllFiles().mkString("\n").split("\n") if "shuffle_" in f}
    before = files()
    table = saved(spark.range(5000).selectExpr("id % 7 AS k").groupBy("k").count())
    assert not [f for f in files() - before if f.endswith(".data")]
    assert table.count() == 7
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "false") == "false"


def test_linked_sets_share_an_element_of_their_prefixes(monkeypatch):
    monkeypatch.setattr(S, "BINS", 64)
    rng = np.random.default_rng(4)
    for levels in (rng.integers(S.ONCE + 1, 40, 64).astype(np.uint8), np.full(64, 255, dtype=np.uint8)):
        for size in [*range(1, 30), 100, 333]:
            a = np.unique(rng.integers(0, 1 << 40, size).astype(np.uint64))
            common = rng.choice(a, -(-4 * len(a) // 5), replace=False)  # the least that may be common: one holds the other
            assert set(S.prefix(a, levels)) & set(S.prefix(np.sort(common), levels)), size


def test_an_entry_takes_the_same_bytes_in_few_and_in_many_slices():
    rng = np.random.default_rng(6)
    sig, node = rng.integers(0, 1 << 63, 100_000, dtype=np.uint64) * np.uint64(2), np.repeat(rng.integers(-(1 << 62), 1 << 62, 500), 200)
    size = {bits: sum(len(pa.compress(b"".join(r), codec="lz4", asbytes=True)) for r in zip(*(S.packed(sig, node, bits, 3).column(c).to_pylist() for c in ("values", "owners")))) for bits in (4, 9)}
    assert size[9] < 1.35 * size[4] and size[9] < 8.5 * len(sig)
    for bits in (4, 9):
        back = [(S.values_of(i, v), S.owners_of(o)) for i, _, v, o, *_ in zip(*(c.to_pylist() for c in S.packed(sig, node, bits, 3).columns)) if v]
        held = np.unique(node)
        assert sorted(zip(*(np.concatenate(x).tolist() for x in zip(*back)))) == sorted(zip((sig >> np.uint64(24 - bits)).tolist(), np.searchsorted(held, node).tolist()))


@pytest.mark.parametrize("pack", [400_000, 900])
def test_elements_counted_one_by_one_give_the_same_components(docs, pack, monkeypatch):
    for name, value in (("BINS", 1 << 6), ("BLOCK", 7), ("LARGE", 5), ("PACK", pack), ("CHUNK", 500)):
        monkeypatch.setattr(S, name, value)
    asked, plain = [], S.prefixes
    monkeypatch.setattr(S, "prefixes", lambda *a: asked.append(1) or plain(*a))
    assert sorted((str(r[0]), r[1], str(r[2])) for r in S.near_copies(docs).collect()) == brute(corpus()) and asked


def test_prefixes_of_counted_elements_begin_with_the_rarest(spark):
    rng = random.Random(8)
    rows = [(k, " ".join(f"w{rng.randrange(4)}" for _ in range(60))) for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    everywhere = spark.sparkContext.broadcast(bytes([255]) * (S.FILTER_BITS // 8))
    sets = {S.digest(s): s >> np.uint64(64 - S.LOW - 6) for s in (S.shingles(words_of(t)) for _, t in rows)}
    counts = Counter(int(e) for s in sets.values() for e in s)
    want = {(d, e) for d, s in sets.items() for e in sorted(s.tolist(), key=lambda e: (counts[e], e))[: len(s) - -(-4 * len(s) // 5) + 1] if counts[e] > 1}
    assert {tuple(r) for r in S.prefixes(docs, everywhere, 6, "doc_id", "text").collect()} == want


def test_pairs_of_blocks_dealt_in_turns_give_the_same_components(docs, monkeypatch):
    turns, plain = [], S.turns_of
    for name, value in (("BLOCK", 4), ("LARGE", 5), ("DEALT", 0.01), ("LEAST_DEALT", 20_000)):
        monkeypatch.setattr(S, name, value)
    monkeypatch.setattr(S, "turns_of", lambda *a: turns.append(plain(*a)) or turns[-1])
    assert sorted((str(r[0]), r[1], str(r[2])) for r in S.near_copies(docs).collect()) == brute(corpus())
    assert turns and turns[0] > 1
