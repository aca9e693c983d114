import numpy as np
import pytest

from evsketch.llm import pq

SCHEMA = "vec_id long, embedding array<float>, label int"


def brute(rows, threshold=0.93):
    root = {i: i for i, _, _ in rows}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    links = dict.fromkeys(root, 0)
    sound = [(i, np.array(v, np.float64), k) for i, v, k in rows if v and k is not None and None not in v and np.isfinite(v).all() and any(v)]
    for i, v, k in sound:
        for j, w, m in sound:
            if i != j and k == m and len(v) == len(w) and v @ w / (np.linalg.norm(v) * np.linalg.norm(w)) >= threshold:
                links[i] += 1
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: (links[i], find(i), find(i) == i) for i in root}


def clustered(seed=3, n=300, dim=24):
    rng = np.random.default_rng(seed)
    centres = rng.normal(size=(12, dim))
    rows = []
    for i in range(n):
        v = centres[rng.integers(12)] + rng.normal(size=dim) * rng.choice([0.05, 0.2, 0.3])
        rows.append((i, [float(np.float32(x)) for x in v], int(rng.integers(3))))
    hot = rows[0][1]
    rows += [(n + i, hot, rows[0][2]) for i in range(120)]  # one vector many times
    return rows


@pytest.mark.parametrize("how", [pq.Index(), pq.Index(sample=60, lists=5, codes=16, block=20, part=50, batch=16)])
def test_links_equal_brute_force(spark, how):
    rows = clustered()
    rows += [(1000, None, 1), (1001, [0.0] * 24, 1), (1002, [None] * 24, 1), (1003, [float("nan")] * 24, 1), (1004, rows[0][1], None), (1005, [1.0, 2.0], 0), (1006, [2.0, 4.0], 0), (1007, [], 0)]
    got = pq.near_vectors(spark.createDataFrame(rows, SCHEMA).repartition(3), how=how).collect()
    assert {r.vec_id: (r.n_links, r.component_id, r.kept) for r in got} == brute(rows)
    assert sum(n for n, _, _ in brute(rows).values()) > 10_000


def test_empty_table_and_repeated_rows(spark):
    assert pq.near_vectors(spark.createDataFrame([], SCHEMA)).count() == 0
    rows = [(5, [1.0, 0.0], 1), (5, [1.0, 0.0], 1), (None, [1.0, 0.01], 1), (7, [0.0, 1.0], 1)]
    got = sorted((r.vec_id or -1, r.n_links, r.component_id) for r in pq.near_vectors(spark.createDataFrame(rows, SCHEMA)).collect())
    assert got == [(-1, 2, 5), (5, 2, 5), (5, 2, 5), (7, 0, 7)]
