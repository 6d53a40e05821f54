"""Vectors of many lengths and sizes, and labels of more than one tile, against all pairs."""

import numpy as np
import pytest

from assetmill.llm import vectors
from assetmill.plans.scratch import Scratch

SCHEMA = "vec_id long, embedding array<double>, label int"


def brute(rows, least=0.98):
    """n_links and component of each row, by every pair."""
    unit = {}
    for i, v, label in rows:
        if label is not None and v is not None and len(v) and all(x is not None and np.isfinite(x) for x in v) and max(map(abs, v)) > 0:
            x = np.array(v) / max(map(abs, v))
            unit[i] = (label, x / np.linalg.norm(x))
    links, root = {i: 0 for i, _, _ in rows}, {i: i for i, _, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(unit)
    for k, a in enumerate(ids):
        for b in ids[:k]:
            if unit[a][0] == unit[b][0] and len(unit[a][1]) == len(unit[b][1]) and unit[a][1] @ unit[b][1] >= least:
                links[a] += 1
                links[b] += 1
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: (links[i], find(i)) for i in links}


def got(spark, rows, **options):
    with Scratch(spark, "lengths") as s:
        return {r.vec_id: (r.n_links, r.component_id) for r in vectors.near_vectors(spark.createDataFrame(rows, SCHEMA).repartition(4), s, **options).collect()}


def cloud(n, dims, groups, seed, noise=0.05):
    rng = np.random.default_rng(seed)
    base = rng.normal(size=(groups, dims))
    return [(base[i % groups] + rng.normal(size=dims) * noise).tolist() for i in range(n)]


@pytest.mark.parametrize("numbers", [vectors.AXIS_NUMBERS, 40])
def test_every_length_is_compared(spark, monkeypatch, numbers):
    """Also where only the shortest lengths get principal axes."""
    monkeypatch.setattr(vectors.principal_axes, "__defaults__", (numbers,))
    rows = []
    for dims in range(1, 41):
        rows += [(len(rows) + k, v, dims % 2) for k, v in enumerate(cloud(6, dims, 2, dims))]
    assert got(spark, rows) == brute(rows)


def test_many_lengths(spark):
    rows = [(2 * d + k, [1.0] * (d - 1) + [1.0 + k], 0) for d in range(1, 260) for k in (0, 1)]
    assert len({len(v) for _, v, _ in rows}) == 259
    assert got(spark, rows) == brute(rows)


def test_tiny_and_huge_vectors(spark):
    v = [[1e-170, 1e-170], [2e-170, 2e-170], [1e200, 1e200], [1e200, -1e200], [5e-324, 5e-324], [1.0, 1.0], [0.0, 0.0], [1e308, 1e308], [float("inf"), 1.0], [None, 1.0], None, [], [1e-170, 1e-150]]
    rows = [(i, x, 0) for i, x in enumerate(v)] + [(50, [1.0, 1.0], None)]
    assert got(spark, rows) == brute(rows)


@pytest.mark.parametrize("tile", [16, 50])
def test_labels_of_many_tiles(spark, tile):
    rows = [(i, v, i % 2) for i, v in enumerate(cloud(500, 12, 40, 5, 0.08))]
    want = brute(rows)
    assert sum(n for n, _ in want.values()) > 500
    assert got(spark, rows, tile=tile) == want


def test_pairs_strip_by_strip(monkeypatch):
    monkeypatch.setattr(vectors, "TILE", 32)
    x = np.array(cloud(300, 10, 20, 6))
    t = vectors._turn(x, {})
    near = lambda i, j: sorted((min(a, b), max(a, b)) for a, b in zip(i.tolist(), j.tolist()))
    want = [(a, b) for a in range(300) for b in range(a + 1, 300) if t[a] @ t[b] >= 0.98]
    assert near(*vectors._pairs(x, t, np.arange(300), None, 0.98)) == want
    assert near(*vectors._pairs(x, t, np.arange(100), np.arange(100, 300), 0.98)) == [p for p in want if p[0] < 100 <= p[1]]
