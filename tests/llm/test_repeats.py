"""Repeated lines and passages against a dictionary of units built word by word."""

import random
import re

from attrition.llm import repeats as R
from attrition.llm.common import word_hashes


def plain_units(text):
    """(words as key, start, end) of each unit, one at a time."""
    found = list(re.finditer(r"[^\x20\x09-\x0D]+", text))
    words = [m[0].encode().lower() for m in found]
    n = len(words)
    line_end = [i == n - 1 or "\n" in text[found[i].end() : found[i + 1].start()] for i in range(n)]
    bound = [line_end[i] or words[i][-1:] in (b".", b"!", b"?") or int(word_hashes([words[i]])[0]) >> 60 == 0 for i in range(n)]
    out = []
    for s in (i for i in range(n) if i == 0 or bound[i - 1]):
        e = next((i + 1 for i in range(s + R.PASSAGE_WORDS - 1, n) if bound[i]), None)
        if e:
            out.append((("p", *words[s:e]), found[s].start(), found[e - 1].end()))
    for s in (i for i in range(n) if i == 0 or line_end[i - 1]):
        e = next(i + 1 for i in range(s, n) if line_end[i])
        if e - s >= R.LINE_WORDS:
            out.append((("l", *words[s:e]), found[s].start(), found[e - 1].end()))
    return out


def expected(rows):
    first, everything = {}, []
    for i, t in sorted(set(rows), key=lambda r: (r[0] is None, r[0] or 0)):
        for k, a, b in plain_units(t or ""):
            everything.append((k, (i is None, i or 0), a, b, i, t))
    for k, i, a, *_ in everything:
        first[k] = min(first.get(k, (i, a)), (i, a))
    lost = {}
    for k, i, a, b, raw, t in everything:
        if (i, a) != first[k]:
            lost.setdefault((raw, t), set()).update(range(a, b))
    return lost


def corpus():
    rng = random.Random(11)
    words = [f"Wörd{i}" for i in range(400)] + ["the", "of", "a"] * 20
    make = lambda n: " ".join(rng.choice(words) + rng.choice(["", "", "", ".", ","]) for _ in range(n))
    passage, line = make(60), "Licensed under some terms that many share today"
    rows = [(i, make(rng.randrange(5, 80)) + "\n" + make(20)) for i in range(30)]
    rows += [(100 + i, f"{make(13)} {passage} {make(9)}") for i in range(6)]
    rows += [(200 + i, f"{make(9)}\n{line}\n{make(9)}") for i in range(5)]
    rows += [(300, rows[3][1]), (None, rows[3][1]), (3, rows[3][1]), (301, None), (302, ""), (303, "of " * 60), (304, "x" * 5000)]
    return rows, passage


def test_spans_equal_the_plain_dictionary(spark):
    rows, passage = corpus()
    docs = spark.createDataFrame([(i, t, "clash") for i, t in rows], "doc_id long, text string, removed string")
    want = {k: v for k, v in expected(rows).items() if v}
    got = R.repeated_spans(docs.repartition(5)).collect()
    texts = {}
    for i, t in rows:
        texts.setdefault(i, []).append(t)
    assert len(got) == len(want)
    by_size = sorted((str(i), len(v), min(v), max(v) + 1) for (i, _), v in want.items())
    cover = lambda spans: set().union(*[range(s["start"], s["end"]) for s in spans])
    assert sorted((str(r["doc_id"]), len(c := cover(r["removed"])), min(c), max(c) + 1) for r in got) == by_size
    assert {r["doc_id"] for r in got} >= {101, 102, 103, 104, 105, 201, 202, 203, 204, 300}
    clean = R.without_repeats(docs)
    left = {r["doc_id"]: r for r in clean.where("doc_id >= 100").collect()}
    assert clean.count() == len(rows)
    inner = passage.split(". ")[2]
    assert inner in left[100]["text"] and all(inner not in left[i]["text"] for i in range(101, 106))
    assert left[301]["text"] is None and left[302]["text"] == ""


def test_result_does_not_depend_on_partitions(spark):
    rows, _ = corpus()
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    one, many = (sorted(map(repr, R.repeated_spans(docs.repartition(n)).collect())) for n in (1, 9))
    assert one == many


def test_empty(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert R.repeated_spans(docs).count() == 0 and R.without_repeats(docs).count() == 0


def test_every_inline_copy_goes_as_a_whole(spark):
    rng = random.Random(5)
    fresh = lambda n: [f"q{rng.randrange(10**9)}" for _ in range(n)]  # noqa: E731  without punctuation
    rows, want = [], {}
    for i, size in enumerate([48, 50, 51, 60, 80, 200] * 25):
        passage = fresh(size)
        rows.append((i, " ".join(fresh(rng.randrange(40)) + passage + fresh(rng.randrange(40)))))
        head, body = " ".join(fresh(rng.randrange(1, 40))), "".join(w + rng.choice("  \n") for w in passage).strip()
        rows.append((1000 + i, f"{head} {body} " + " ".join(fresh(rng.randrange(40)))))
        want[1000 + i] = [(len(head) + 1, len(head) + 1 + len(body))], [i]
    rows.append((5000, "of " * 60))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: ([tuple(s) for s in r["removed"]], r["kept_ids"]) for r in R.repeated_spans(docs, gap=R.GAP).collect()}
    (start, end), = got.pop(5000)[0]
    assert start >= len("of " * R.PASSAGE_WORDS) - 1 and end == len("of " * 60) - 1, "the first one stays whole"
    assert got == want
    assert R.repeated_spans(docs.limit(0), gap=R.GAP).count() == 0
