"""Connected components on shapes that are slow for least labels."""

import random

import pytest

from bigtopics.operators import graph


def brute(edges):
    up = {x: x for e in edges for x in e}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {x: find(x) for x in up}


@pytest.mark.parametrize("kind", ["path", "star", "random", "two"])
def test_components(spark, kind, monkeypatch):
    rounds, write = [], graph.settle
    monkeypatch.setattr(graph, "settle", lambda df, name: (rounds.append(name), write(df, name))[1])
    r = random.Random(3)
    order = [0, *range(255, 0, -1)]
    edges = {"path": list(zip(order, order[1:])), "star": [(200, k) for k in range(200)], "random": [(r.randrange(300), r.randrange(300)) for _ in range(180)], "two": [(1, 2), (2, 1), (5, 4), (4, 4)]}[kind]
    got = {x.node: x.label for x in graph.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == brute([(a, b) for a, b in edges if a != b])
    assert rounds.count("stars") <= 12


def test_no_links(spark):
    assert graph.components(spark.createDataFrame([], "a bigint, b bigint")).count() == 0
