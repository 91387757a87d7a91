"""Personal data: base rules against plain regular expressions, and discovery from context."""

import re

import pytest
from attrition.llm import private_data as P
from hypothesis import given, settings
from hypothesis import strategies as st

RULES = (
    (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(p) <= 255 for p in m.split("."))),
    (r"[0-9]([\x20-]?[0-9])+", lambda m: 16 <= len(d := re.sub(r"\D", "", m)) <= 19 and checked(d)),
    (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 8 <= sum(c in "0123456789" for c in m) <= 15),
)


def checked(digits):
    doubled = [int(c) * (1 + i % 2) for i, c in enumerate(digits[::-1])]
    return sum(d - 9 if d > 9 else d for d in doubled) % 10 == 0


def brute(text):
    return [(k, *m.span()) for k, (rule, good) in enumerate(RULES) for m in re.finditer(rule, text or "") if good(m[0])]


@settings(max_examples=400, deadline=None)
@given(st.lists(st.sampled_from(["a", "b.c", "@", ".", "-", " ", "+", "1", "22", "255", "256", "4111 1111 1111 1111", "é", "(", ")", "+49 30 1234567", "x@y.z", "\n"]), max_size=25).map("".join))
def test_base_rules_equal_plain_regular_expressions(text):
    assert P.base_spans(text) == brute(text)


def test_very_long_runs_take_linear_time():
    for text in ("a" * 400_000, "1" * 400_000, "1." * 200_000, "+1" + " " * 300_000, "a@" * 100_000, "a." * 100_000 + "@"):
        P.base_spans(text)
        P.loose_spans(text, [])


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, f"Please call hotline: +49 30 5550{i:03d} or write.", "x") for i in range(12)]
    rows += [(100 + i, f"Please call hotline: 030 7770{i:03d} now.", "x") for i in range(3)]
    rows += [(200, "The number 0307771234 is a product code.", "x"), (201, None, "x"), (202, "", None), (None, "hotline: +49 30 5550001", "x"), (0, "hotline: 030 7770001", "x")]
    return spark.createDataFrame(rows, "doc_id long, text string, spans string")


def test_context_discovers_unseen_identifiers_and_keeps_the_base(docs):
    got = {(r["doc_id"], r["n_found"]): r for r in P.spans(docs).collect()}
    assert len(got) == docs.count()
    assert all(got[(i, 0)]["n_phone"] == 1 for i in range(1, 12))
    assert all((100 + i, 1) in got and got[(100 + i, 1)]["spans"].startswith("phone:21:") for i in range(3))
    assert (0, 1) in got and (0, 0) in got, "rows that share an id keep their own spans"
    assert got[(200, 0)]["spans"] == "" and got[(201, 0)]["base"] == "" and (None, 0) in got


def test_redaction_masks_spans_and_keeps_rows(docs):
    out = P.redacted(docs)
    assert out.columns == docs.columns
    texts = sorted(str(r["text"]) for r in out.collect())
    assert len(texts) == docs.count() and sum("[PHONE]" in t for t in texts) == 17 and not any("777000" in t for t in texts)
    assert "The number 0307771234 is a product code." in texts


def test_empty_table(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert P.spans(empty).count() == 0 and P.redacted(empty).count() == 0


def test_contexts_with_other_spaces_and_long_words(spark):
    for word in ("t\u00e9l\u00e9phone\u00a0:", "numero-" * 8 + "appel:"):
        rows = [(i, f"Notre {word} +49 30 5550{i:03d} merci") for i in range(12)] + [(100, f"Notre {word} 030 7770001 bientot")]
        found = {r["doc_id"]: r["n_found"] for r in P.spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
        assert found[100] == 1, word


def test_labels_that_touch_the_identifier_discover_as_spaced_ones(spark):
    for glue in (" ", ":", "=", ": ", "=\t", "/", '="'):
        label = {" ": "hotline:", "/": "tel"}.get(glue, "hotline")
        rows = [(i, f"Ask {label}{glue}+49 30 5550{i:03d} or write.") for i in range(12)]
        rows += [(100 + i, f"Ask {label}{glue}030 7770{i:03d} or write.") for i in range(3)]
        got = {r["doc_id"]: r["n_found"] for r in P.spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
        assert sum(got[100 + i] for i in range(3)) == 3, glue


def test_words_of_the_border_count_against_a_pattern(spark):
    rows = [(i, f"x{i} code={('+49 30 5550%03d' if i < 4 else 'item%d') % i} y{i}") for i in range(300)]
    rows += [(1000, "x code=030 7770001 z")]
    got = {r["doc_id"]: r["n_found"] for r in P.spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1000] == 0, "the word stands beside other things as a rule"


@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from(["ab", "c:", "=", " ", "\n", "1.2.3.4", "x@y.z", "+49 30 1234567", "030 7770001", "\u00a0", "long" * 30, "(", "."]), max_size=14).map("".join))
def test_contexts_are_words_of_the_text_cut_at_spans(text):
    base = P.base_spans(text)
    spans = base + P.loose_spans(text, base)
    borders = {x for _, a, b in spans for x in (a, b)}
    plain = [m.span() for m in P.TOKEN.finditer(text)]
    parts = []  # words cut at every border
    for a, b in plain:
        at = [a, *sorted(x for x in borders if a < x < b), b]
        parts += [(x, y, (x, y) != (a, b)) for x, y in zip(at, at[1:])]
    for (_, a, b), (left, right, made, after) in zip(spans, P.contexts(text, spans)):
        before = [p for p in parts if p[0] < a and p[1] <= a]
        behind = [p for p in parts if p[1] > b and p[0] >= b]
        assert (left, made) == ((P.cleaned(text[before[-1][0] : before[-1][1]]), int(before[-1][2])) if before else ("", 0))
        assert (right, after) == ((P.cleaned(text[behind[0][0] : behind[0][1]]), int(behind[0][2])) if behind else ("", 0))


def test_long_numbers_are_candidates_and_clashing_names_stay(spark):
    cards = ("4111 1111 1111 1111", "4012 8888 8888 1881", "5555 5555 5555 4444", "5105-1051-0510-5100")
    rows = [(i, f"card: {c} ok{i}") for i, c in enumerate(cards * 2)] + [(50, "card: 4 1 1 1 1 1 1 1 1 1 1 1 1 1 1 1 1 1 2 ok")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "7 AS _digest", "'m' AS _more", "8 AS digest", "'f' AS found", "9 AS _found")
    out = P.redacted(docs)
    assert out.columns == docs.columns
    kept = {tuple(r[2:]) for r in out.collect()}
    assert kept == {(7, "m", 8, "f", 9)} and all("[CARD]" in r["text"] for r in out.collect())
