"""Language-model scoring: the base against plain counting, the model against a one-text-at-a-time version."""

import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from attrition.llm import scoring as S
from attrition.llm.common import words_of

VOCABULARY = public_tokenizers.path("byte_bpe_50k.tiktoken")


@pytest.fixture(scope="module")
def rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").limit(60)
    more = [(900, None), (901, ""), (902, " \n"), (None, "The of and"), (903, "x" * 3000), (903, "x" * 3000), (904, "Ünïcode İ \x85 word")]
    return docs.union(docs.sparkSession.createDataFrame(more, docs.schema))


@pytest.mark.parametrize("common", [S.COMMON, 50])
def test_base_equals_plain_counting(rows, common, monkeypatch):
    monkeypatch.setattr(S, "COMMON", common)  # 50: most words take the way of the looked-up ones
    got = S.scores(rows.withColumnRenamed("text", "text"), VOCABULARY, steps=20).collect()
    given = [(r[0], r[1]) for r in rows.collect()]
    held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 7 == 2
    counts = Counter()
    for i, t in given:
        if not held(i):
            counts.update([*words_of(t), None])
    total, distinct = sum(counts.values()), len(counts)
    want = sorted(
        (str(i), held(i), len(words_of(t)) + 1, sum(counts[w] > 0 for w in [*words_of(t), None]), total,
         round(sum(np.log10((counts[w] + 1) / (total + distinct + 1)) for w in [*words_of(t), None]), 6)) for i, t in given
    )
    assert sorted((str(r[0]), *r[1:5], round(r["base_score"], 6)) for r in got) == want
    assert all(np.isfinite(r["score"]) and r["score"] < 0 for r in got)


def plain_share(model, pairs, before, target):
    """log10 share of an id in its class after another, from a dictionary of counts."""
    row, own = int(model.row_of[before]), int(model.class_of[target])
    inside = sum(n for (r, i), n in pairs.items() if r == row and model.class_of[i] == own)
    return np.log10((pairs.get((row, int(target)), 0) + S.WEIGHT * 10.0 ** float(model.share[target])) / (inside + S.WEIGHT))


def plain_score(model, ids, pairs=None):
    """One target at a time, with the context its window gives it."""
    total, n, step = 0.0, len(ids) - 1, S.WINDOW - S.OVERLAP
    for t in range(n):
        j = 0 if t < S.WINDOW else 1 + (t - S.WINDOW) // step
        start = min(j * step, max(0, n - S.WINDOW))
        seq = ids[start : t + 1]
        x = model.embed[model.row_of[seq]].astype(float) + model.place[: len(seq)]
        q, k, v = np.split(x @ model.qkv, 3, axis=1)
        a = np.exp(q[-1] @ k.T)
        z = (x[-1] + a @ v / a.sum()) @ model.out + model.after[model.row_of[ids[t]]]
        total += (z[model.class_of[ids[t + 1]]] - np.log(np.exp(z).sum())) / np.log(10) + plain_share(model, pairs or {}, ids[t], ids[t + 1])
    return total


def counted(texts, totals):
    """Plain counts of (embedding row, id after it), as a dictionary and as sorted keys and counts."""
    row_of = S.classes(totals)[0]
    pairs = Counter((int(row_of[a]), int(b)) for ids in texts for a, b in zip(ids, ids[1:]))
    keys = sorted(r << 16 | i for r, i in pairs)
    return pairs, (np.array(keys, dtype=np.uint32), np.array([pairs[k >> 16, k & 65535] for k in keys], dtype=np.int64))


def test_each_id_is_scored_once_and_the_model_is_a_distribution():
    speller = S.Speller(VOCABULARY)
    texts = [words_of(t) for t in ("", "the cat sat", "one two three four " * 30, "a b c " * 9 + "d", "zz " * 31)]
    windows = speller.windows(texts)
    totals = np.bincount(windows.flat, minlength=50257)
    ids = [np.frombuffer(speller.end + speller.known.joined(t) + speller.end, dtype=np.uint16) for t in texts]
    pairs, table = counted(ids[:3], totals)
    model = S.train(windows, totals, steps=60, pairs=table)
    assert np.allclose(S.score_texts(model, windows), [plain_score(model, i, pairs) for i in ids], rtol=1e-4)
    every = np.arange(50257, dtype=np.uint16)
    for before in (ids[1][1], ids[2][2], 40_000):  # shares of each class add up to one, whatever stands before
        logs = model.pairs.logs(np.full(50257, model.row_of[before]), every, model.class_of, model.share)
        assert np.allclose(np.bincount(model.class_of, weights=10.0 ** logs.astype(float)), 1, atol=1e-3)
    assert S.score_texts(S.train(None, np.zeros(50257, dtype=int)), windows)[2] < S.score_texts(model, windows)[2], "training helps"


def test_scores_do_not_leave_single_precision_or_depend_on_neighbours():
    speller, rng = S.Speller(VOCABULARY), np.random.default_rng(3)
    texts = [words_of("one two three " * n) for n in (1, 30, 200)] + [words_of(" ".join(f"w{rng.integers(99)}" for _ in range(300)))]
    totals = np.bincount(speller.windows(texts).flat, minlength=50257)
    model = S.train(None, totals)
    model.embed, model.qkv, model.out = (rng.normal(0, 30, a.shape).astype(np.float32) for a in (model.embed, model.qkv, model.out))
    model = model.held()
    together = S.score_texts(model, speller.windows(texts))
    assert np.isfinite(together).all()
    assert np.allclose(together, [S.score_texts(model, speller.windows([t]))[0] for t in texts], rtol=1e-4)


def test_the_model_has_its_full_size():
    n = 500
    texts = S.Windows(np.zeros(n + 1, dtype=np.uint16), np.array([n + 1]))
    _, _, counts = texts.part(slice(0, len(texts)))
    assert counts.sum() == n and counts[1:].argmax(axis=1).min() >= 8, "least context of an id past the first window"
    _, class_of, share = S.classes(np.arange(1, 5001)[::-1])
    assert len(set(class_of)) == 128 and np.isclose(share, 0, atol=1e-6).sum() == 104


def test_counts_come_from_whole_texts(spark):
    late = "filler " * 1000 + "ping pong " * 40  # past character 4000
    texts = [late, "", None, "alone", late]
    docs = spark.createDataFrame([*enumerate(texts)], "doc_id long, text string").repartition(3)
    speller = S.Speller(VOCABULARY)
    ids = [np.frombuffer(speller.end + speller.known.joined(words_of(t)) + speller.end, dtype=np.uint16) for t in texts]
    totals = sum(np.bincount(i[1:], minlength=50257) for i in ids)
    mapped = S.gathered(docs, VOCABULARY, 1.0).cache()
    assert {r["word"]: r["n"] for r in mapped.where("word is not null").groupBy("word").agg({"n": "sum"}).toDF("word", "n").collect()} == Counter(w for t in texts for w in words_of(t))
    pairs = mapped.where("pair is not null").groupBy("pair").agg({"n": "sum"}).toDF("pair", "n")
    assert (S.id_totals(pairs, 50257) == totals).all()
    row_of, class_of, _ = S.classes(totals)
    follows, keys, counts = S.followers(pairs, totals)
    want = Counter((int(row_of[a]), int(class_of[b])) for i in ids for a, b in zip(i, i[1:]))
    assert {(int(r), int(c)): int(follows[r, c]) for r, c in zip(*np.nonzero(follows))} == want
    _, table = counted(ids, totals)
    assert (keys == table[0]).all() and (counts == table[1]).all()
    drawn = S.drawn_windows(mapped)
    assert drawn.counts.sum() == totals.sum(), "every window may be drawn"
    assert 0 < len(S.drawn_windows(S.gathered(docs, VOCABULARY, 0.1))) < len(drawn) / 3
    model = S.train(drawn, totals, steps=3, follows=follows, pairs=(keys, counts))
    score = lambda t: S.score_texts(model, speller.windows([words_of(t)]))[0]
    assert score("ping pong ping pong ping pong") > score("pong pong ping ping pong ping") + 1


def test_a_cut_keeps_the_commonest(spark):
    counts = spark.createDataFrame([(n,) for n in [1] * 50 + [2] * 20 + [3] * 9 + [500, 1000]], "n long")
    assert [S.cut_of(counts, most) for most in (0, 1, 2, 10, 11, 30, 31, 80, 81, 10**6)] == [1001, 1000, 500, 500, 3, 3, 2, 2, 1, 1]
    assert S.cut_of(counts.limit(0), 10) == 1


def test_the_model_beats_the_base_on_held_out_text(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    got = S.scores(docs, VOCABULARY).where("held_out").agg({"score": "sum", "base_score": "sum"}).first()
    assert got["sum(score)"] > got["sum(base_score)"]


def test_empty(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert S.scores(empty, VOCABULARY, steps=2).count() == 0


def small_texts(spark):
    rng = np.random.default_rng(1)
    texts = [" ".join(rng.choice(["one", "two", "three", "four"], 40)) for _ in range(30)] + ["red x x blue. green x x black. " * 20] * 10
    return texts, spark.createDataFrame([*enumerate(texts)], "doc_id long, text string").repartition(3).cache()


def test_slopes_equal_differences():
    speller, rng = S.Speller(VOCABULARY), np.random.default_rng(2)
    windows = speller.windows([words_of(t) for t in ("red x x blue. green x x black. " * 8, "a b", "")])
    model = S.train(windows, np.bincount(windows.flat, minlength=50257), steps=30)
    learner = S.Learner(model)
    learner.p = {n: (a + rng.normal(0, 0.05, a.shape)).astype(np.float64) for n, a in learner.p.items()}
    part = windows.part(np.arange(len(windows)))
    _, slopes = learner.slopes(*part)
    near = model.row_of[part[0][0, :3]]
    for name, at in [("out", (3, 5)), ("bias", (2,)), ("qkv", (1, 2)), ("qkv", (4, 20)), ("qkv", (7, 40)), ("place", (3, 3)), ("embed", (near[1], 4)), ("embed", (near[2], 9))]:
        own, values = learner.p[name][at], []
        for step in (1e-4, -1e-4):
            learner.p[name][at] = own + step
            values.append(learner.slopes(*part)[0])
        learner.p[name][at] = own
        assert np.isclose((values[0] - values[1]) / 2e-4, slopes[name][at], rtol=2e-2, atol=2e-4), (name, at)


def test_weights_are_taught_by_every_window(spark):
    texts, docs = small_texts(spark)
    speller = S.Speller(VOCABULARY)
    parts = [[words_of(r["text"]) for r in part] for part in docs.rdd.glom().collect()]
    windows = [speller.windows(p) for p in parts]
    model = S.train(None, sum(np.bincount(w.flat, minlength=50257) for w in windows))
    got = S.learnt(model, docs, VOCABULARY)
    learners = [S.Learner(model) for _ in parts]
    for learner, w in zip(learners, windows):
        learner.add(w)
    assert sum(x.windows for x in learners) == sum(map(len, windows)), "every window"
    want = learners[0].with_weights(np.average([x.raw() for x in learners], axis=0, weights=[x.windows for x in learners]))
    for name in ("embed", "place", "qkv", "out", "after"):
        assert np.allclose(getattr(got, name), getattr(want, name), atol=1e-5), name
    assert sum(S.score_texts(got, w).sum() for w in windows) > sum(S.score_texts(model, w).sum() for w in windows)


def test_scores_do_not_hang_on_the_windows_drawn_first(spark, monkeypatch):
    _, docs = small_texts(spark)
    total = lambda: S.scores(docs, VOCABULARY, most=0, steps=1).agg({"score": "sum"}).first()[0]
    taught = total()
    monkeypatch.setattr(S, "learnt", lambda model, *_: model)
    assert taught > total(), "without a single window drawn, attention is taught by the texts"
