"""Decontamination: the masks' promise, and leaks against a search of all alignments."""

import itertools
import random

from attrition.llm import leaks as L


def test_masks_hit_every_window_with_two_misses():
    for misses in itertools.combinations(range(L.SPAN), L.ALLOWED):
        assert any(
            all(o + p not in misses for p in L.kept_places(m)) for m in L.MASKS for o in range(L.SPAN - len(m) + 1)
        ), misses


def brute(item, text):
    """Positions of texts covered by windows that agree, on every alignment."""
    a, b = L.tokens(item), L.tokens(text)
    w = min(L.SPAN, len(a))
    found = set()
    if len(a) >= L.LEAST:
        for i in range(len(a) - w + 1):
            for j in range(len(b) - w + 1):
                if sum(x == y for x, y in zip(a[i : i + w], b[j : j + w])) >= w - L.allowed(w):
                    found.add((j - i, j))
    return found


def test_finder_equals_search_of_all_alignments():
    rng = random.Random(5)
    words = [f"w{i}" for i in range(30)] + ["the"] * 6
    for _ in range(60):
        items = [(i, " ".join(rng.choice(words) for _ in range(rng.choice([3, 5, 6, 8, 12, 13, 14, 30])))) for i in range(4)]
        texts = []
        for _ in range(6):
            t = [rng.choice(words) for _ in range(rng.randrange(40))]
            if rng.random() < 0.8:
                piece = rng.choice(items)[1].split()
                for _ in range(rng.randrange(4)):
                    piece[rng.randrange(len(piece))] = "zzz"
                at = rng.randrange(len(t) + 1)
                t[at:at] = piece
            texts.append(", ".join(t).upper())
        texts += [None, ""]
        got = L.Finder(L.SeedIndex.build(items)).search(texts)
        for t, hits in zip(texts, got):
            for i, item in items:
                want = brute(item, t)
                assert bool(want) == any(h[0] == i for h in hits), (item, t)
                mine = [h for h in hits if h[0] == i]
                w = min(L.SPAN, len(L.tokens(item)))
                assert all(any(h[1] <= j and j + w <= h[2] for h in mine) for _, j in want)


def test_rows_spans_and_odd_input(spark):
    passage = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron"
    items = spark.createDataFrame([(7, passage), (8, None), (9, "too short")], "item_id long, text string")
    rows = [(1, f"Éa {passage.upper()}. end"), (1, f"Éa {passage.upper()}. end"), (2, "nothing here"), (3, None), (None, passage), (4, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS item_id", "'x' AS n_equal")
    got = sorted((str(r[0]), *r[1:]) for r in L.leaks(docs, items).collect())
    assert got == [("1", 7, 3, 3 + len(passage), 15, 15)] * 2 + [("None", 7, 0, len(passage), 15, 15)]
    left = L.without_leaks(docs, items)
    assert left.columns == docs.columns and sorted(str(r[0]) for r in left.collect()) == ["2", "3", "4"]
    assert L.leaks(docs.limit(0), items).count() == 0 and L.leaks(docs, items.limit(0)).count() == 0
