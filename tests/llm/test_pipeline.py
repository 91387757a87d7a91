"""The corpus pipeline on planted documents, stage by stage and as a whole."""

import hashlib
import random
import re
from collections import Counter

import corpus_pipeline as C
import pytest
from attrition.llm import language, leaks, queries
from attrition.llm.common import words_of
from pyspark.sql import functions as F


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rng = random.Random(9)
    at = str(tmp_path_factory.mktemp("sf"))
    words = ["the", "of", "river", "stone", "house", "light", "paper", "winter", "garden", "letter", "music", "number", "window", "market", "silver", "forest"]
    more = [a + b for a in words for b in words]
    make = lambda n: " ".join(rng.choice(words + more) for _ in range(n))
    item = make(40)
    rows = [(i, make(60), "en", f"s{i % 3}") for i in range(60)]
    rows += [(100, rows[7][1], "en", "s0"), (101, rows[8][1] + " end", "en", "s1"), (102, make(20) + " " + item + " " + make(20), "en", "s2"), (103, "12 34 !!", "en", "s0"), (104, None, None, None), (105, make(30) + " mail me at jane.roe@example.org now " + make(5), "en", None)]
    spark.createDataFrame([(*r, len(r[1] or "")) for r in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{at}/benchmark.parquet")
    return at


def test_run(spark, folder):
    out = C.run(spark, folder)
    assert out.columns == list(C.COLUMNS)
    rows = out.collect()
    ids = {r["doc_id"] for r in rows}
    assert not ids & {100, 101, 102, 103, 104}
    assert all("jane.roe" not in r["text"] and (r["doc_id"] != 105 or "[EMAIL]" in r["text"]) for r in rows)
    assert ids <= {*range(60), 105} and len(rows) > len(ids) > 40


def test_stages_keep_clean_documents_and_columns(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for name, stage in C.STAGES[:4]:
        out = stage(spark, docs, folder)
        assert out.columns == docs.columns, name
        assert {r["doc_id"] for r in out.select("doc_id").collect()} >= {*range(60)}, name


def test_stages_take_an_empty_table(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(0)
    for name, stage in C.STAGES:
        assert stage(spark, docs, folder).count() == 0, name


def test_all_ten_are_registered():
    assert sorted(int(k[2:].split("_")[0]) for k in queries.queries()) == list(range(1, 11))
    assert set(queries.oracle_sql()) <= set(queries.queries())


def plain_mix(rows):
    """Copies of each row, by water-filling source by source and one coin a row."""
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    own = Counter()
    for r in rows:
        own[r["source"]] += size(r["text"])
    order = sorted(own, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    target, free, left = {}, set(own), 1.5 * sum(own.values())
    while True:
        level = left / sum(weight[s] for s in free) if free else 0
        cut = {s for s in free if 2 * own[s] <= level * weight[s]}
        if not cut:
            break
        target |= {s: 2.0 * own[s] for s in cut}
        left -= sum(2.0 * own[s] for s in cut)
        free -= cut
    target |= {s: level * weight[s] for s in free}
    out = Counter()
    for r in rows:
        rate = target[r["source"]] / own[r["source"]] if own[r["source"]] else 0
        coin = int(hashlib.md5(f"{'' if r['doc_id'] is None else r['doc_id']}|mix".encode()).hexdigest()[:8], 16) / 2**32
        n = int(rate) + (coin < rate - int(rate))
        if n:
            out[tuple(r[c] for c in C.COLUMNS)] += n
    return out


def test_run_equals_a_plain_version(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    net = language.fit(docs).folded()
    rows = [r.asDict() for r in docs.collect()]
    labels, scores = net.judge([r["text"] for r in rows])
    rows = [r for r, a, x in zip(rows, labels, scores) if a != "und" and x >= 0.3]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in (words_of(r["text"]) for r in rows)]
    group = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = group[i], group[j]
                group = [b if g == a else g for g in group]
    rows = [min((r for r, h in zip(rows, group) if h == g), key=lambda r: r["doc_id"]) for g in set(group)]
    items = [leaks.tokens(r[1]) for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect()]
    alike = lambda a, b: sum(x == y for x, y in zip(a, b)) >= len(a) - 2
    leaked = lambda t: any(alike(i[x : x + 13], t[y : y + 13]) for i in items for x in range(len(i) - 12) for y in range(len(t) - 12))
    rows = [r for r in rows if not leaked(leaks.tokens(r["text"]))]
    for r in rows:
        r["text"] = re.sub(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "[EMAIL]", r["text"])
    assert Counter(map(tuple, C.run(spark, folder).collect())) == plain_mix(rows)


def test_stages_take_nulls_repeats_long_texts_and_clashing_columns(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    long = "the long river of stone " * 20_000
    odd = spark.createDataFrame([(None, "alone " * 9, None, None, None), (None, None, None, None, None), (1, "", "en", "s0", 0), (900, long, "en", "s1", 1), (900, long, "en", "s1", 1), (901, "日本語 テキスト " * 30, "ja", "s2", 2)], docs.schema)
    both = docs.union(odd)
    for name in ("_source", "_rate", "_copy", "_more", "_digest", "_id", "seen", "rate", "copy", "node", "text_", "digest", "words"):
        both = both.withColumn(name, F.lit("own"))
    for name, stage in C.STAGES:
        out = stage(spark, both, folder)
        assert out.columns == list(C.COLUMNS), name
        assert out.count() > 40, name
