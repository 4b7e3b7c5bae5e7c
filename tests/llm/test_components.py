"""Connected components: few edges in one task, many by steps, both against a plain union."""

import random

import pytest

from phraseloom.llm import components as c


def brute(edges):
    root = {x: x for e in edges for x in e if e[0] != e[1]}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        if a != b:
            low, high = sorted((find(a), find(b)))
            root[high] = low
    return {x: find(x) for x in root}


@pytest.mark.parametrize("few", [1 << 19, 0])
def test_components_match_a_plain_union(spark, few, monkeypatch):
    monkeypatch.setattr(c, "FEW", few)
    r = random.Random(3)
    names = [r.getrandbits(64) - (1 << 63) for _ in range(120)]
    edges = [(names[i], names[i + 1]) for i in range(40)] + [tuple(r.sample(names[40:], 2)) for _ in range(50)] + [(names[0], names[0]), (names[1], names[0])]
    found = c.components(spark.createDataFrame(edges, "a long, b long").repartition(3)).collect()
    assert len(found) == len({x["node"] for x in found}) and {x["node"]: x["root"] for x in found} == brute(edges)
    assert c.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_few_edges_make_no_steps(spark, monkeypatch):
    monkeypatch.setattr(c, "_star", None)
    assert sorted(tuple(x) for x in c.components(spark.createDataFrame([(5, 3), (3, 9)], "a long, b long")).collect()) == [(3, 3), (5, 3), (9, 3)]
