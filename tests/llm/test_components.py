"""Connected components against a plain union-find: stars, long paths, repeats, many partitions."""

import random

import numpy as np
import pytest

from evsketch.llm import common


def plain(edges):
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {x: find(x) for x in list(root) if find(x) != x}


def graphs():
    rng = random.Random(5)
    names = rng.sample(range(-(10**12), 10**12), 700)
    yield []
    yield [(4, 4), (9, 9)]
    yield list(zip(names, names[1:]))  # one long path in random order of names
    yield [(names[0], x) for x in names[1:]] * 2
    yield [(rng.choice(names), rng.choice(names)) for _ in range(500)]
    yield [(x, x + 1) for x in range(400)] + [(1000 - x, 999 - x) for x in range(300)]


@pytest.mark.parametrize("parts", [1, 7])
def test_components_are_those_of_union_find(spark, parts):
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", str(parts == 1).lower())
    try:
        for edges in graphs():
            df = spark.createDataFrame(edges, "a long, b long").repartition(parts)
            rows = common.components(df).collect()
            assert len({r.node for r in rows}) == len(rows)
            assert {r.node: r.root for r in rows} == plain(edges)
    finally:
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "true")


def test_contraction_keeps_the_components(spark):
    rng = np.random.default_rng(2)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 3000, (2500, 2)) if a != b]
    some = common.contracted(spark.createDataFrame(edges, "a long, b long").repartition(5)).collect()
    assert len(some) <= len(edges) and plain([(r.a, r.b) for r in some]) == plain(edges)
