"""Connected components against a plain search, whole chunks at once and a few edges at a time, with nodes of many edges."""

import random

import pytest
from attrition.llm import components as C


@pytest.mark.parametrize("chunk,hot", [(C.CHUNK, C.HOT), (1, 5), (7, C.HOT)])
def test_components(spark, chunk, hot, monkeypatch):
    monkeypatch.setattr(C, "CHUNK", chunk)
    monkeypatch.setattr(C, "HOT", hot)
    monkeypatch.setattr(C, "MOST_HOT", 1000)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "3" if chunk < 100 else "10000")
    rng = random.Random(2)
    edges = [(rng.randrange(-50, 50), rng.randrange(-50, 50)) for _ in range(45)] + [(i, i + 1) for i in range(1000, 1060)] + [(5000, 5000 + i) for i in range(40)] + [(7, 7)]
    near = {}
    for a, b in edges:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    want, seen = {}, set()
    for n in sorted(near):
        stack = [n] if n not in seen else []
        while stack:
            x = stack.pop()
            if x not in seen:
                seen.add(x)
                want[x] = n
                stack += near[x]
    got = C.components(spark.createDataFrame(edges, "a long, b long"))
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert sorted(map(tuple, got.collect())) == sorted(want.items())


def test_empty(spark):
    assert C.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_few_edges_in_many_tasks_are_contracted_once(spark, monkeypatch):
    calls, plain = [], C.contracted
    monkeypatch.setattr(C, "contracted", lambda edges: calls.append(edges.rdd.getNumPartitions()) or plain(edges))
    edges = spark.range(400).selectExpr("id AS a", "id + 1 AS b").repartition(40)
    assert {tuple(r) for r in C.components(edges).collect()} == {(i, 0) for i in range(401)}
    assert calls == [1]
