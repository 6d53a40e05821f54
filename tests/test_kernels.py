"""Worked examples and numerical properties."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from assetmill.operators import allocation, captions, catalog, costmodel, curriculum, mathkit, quality, routing, textrender
from assetmill.operators.components import components
from assetmill.operators.ranks import place_in_group
from assetmill.plans.scratch import Scratch
from assetmill.workloads import extensions

rng = np.random.default_rng(5)


def test_capacities():
    assert [routing.capacity(*x) for x in ((8, 256, 64), (2, 256, 64), (4, 1024, 64), (2, 7, 64))] == [32, 8, 64, 1]


def test_grouped_products_agree():
    x = [rng.normal(size=(n, 5)) for n in (3, 0, 7, 1)]
    w = rng.normal(size=(4, 5, 6))
    for f in (routing.loop_matmul, routing.padded_matmul):
        assert all(np.allclose(a, b) for a, b in zip(routing.ragged_matmul(x, w), f(x, w)))


def test_swiglu_fused_and_not():
    x, w1, w3, w2 = rng.normal(size=(4, 5)), rng.normal(size=(5, 6)), rng.normal(size=(5, 6)), rng.normal(size=(6, 5))
    assert np.allclose(routing.swiglu(x, w1, w3, w2), routing.swiglu(x, w1, w3, w2, fused=False))


def test_attention():
    q, k, v = rng.normal(size=(16, 6, 8)), rng.normal(size=(4, 6, 8)), rng.normal(size=(4, 6, 8))
    assert np.allclose(mathkit.gqa(q, k, v), mathkit.gqa(q, np.repeat(k, 4, 0), np.repeat(v, 4, 0)))
    x, pos = rng.normal(size=(5, 12)), rng.integers(0, 9, size=(5, 3)).astype(float)
    r = mathkit.rotary(x, pos, (4, 4, 4))
    assert np.allclose(np.linalg.norm(r, axis=1), np.linalg.norm(x, axis=1))
    s = mathkit.rotary(x, pos + 3, (4, 4, 4))
    assert np.allclose(r @ r.T, s @ s.T)


def test_flow_integration_is_exact_for_the_true_velocity():
    z1, x0 = rng.normal(size=8), rng.normal(size=8)
    assert np.allclose(mathkit.integrate(z1, lambda z, t: x0 - z1, lambda z, t: x0 - z1), x0)


def test_router_regularizers():
    w = rng.normal(size=(12, 5))
    a, b = mathkit.ortho_loss(w)
    stepped = sum(mathkit.ortho_loss(mathkit.ortho_step(w, 1.0)))
    assert b == pytest.approx(0) and stepped < a
    eps, grad = 1e-6, (w - mathkit.ortho_step(w, 1.0))
    e = np.zeros_like(w)
    e[3, 2] = eps
    assert (sum(mathkit.ortho_loss(w + e)) - sum(mathkit.ortho_loss(w - e))) / (2 * eps) == pytest.approx(grad[3, 2], rel=1e-3)


def test_optimizers_and_schedules():
    assert np.allclose(np.linalg.svd(mathkit.newton_schulz(rng.normal(size=(6, 4)), 40))[1], 1, atol=1e-3)
    c = mathkit.geometric_weights(9, 0.9)
    assert sum(c) == pytest.approx(1) and mathkit.implied_decay(c)[3] == pytest.approx(1 - 0.9**7)
    assert all(sum(mathkit.merge_weights(s, 16)) == pytest.approx(1) for s in ("mean", "geometric", "printed", "derived", "last"))
    w, g = np.ones(3), np.array([0.1, -0.2, 0.0])
    assert np.allclose(mathkit.adamw_step(w, g, 0 * g, 0 * g, 1, lr=0.1, decay=0)[0], [0.9, 1.1, 1.0], atol=1e-6)


def test_costs():
    assert costmodel.kv_cache(32, 4096, 4) == 268_435_456 and costmodel.kv_cache(32, 4096, 16) == 1_073_741_824
    assert costmodel.fused_traffic() == pytest.approx(1 / 3)
    assert {costmodel.tokens_per_step(b, s) for _, s, b, *_ in routing.STAGES} == {1_048_576}


def test_routing_bounds(spark):
    rows = spark.createDataFrame([(0.29999,), (0.30,), (0.65,), (0.65001,), (None,)], "s double")
    assert [r[0] for r in rows.select(captions.route(F.col("s"))).collect()] == ["synthesize", "refine", "refine", "preserve", "synthesize"]


def test_wavelet_keeps_energy(spark):
    g = spark.createDataFrame([([float(x) for x in rng.normal(size=64)],)], "g array<double>")
    bands = mathkit.haar(F.col("g"))
    a, b = g.select(mathkit.dot(F.col("g"), F.col("g")), sum((mathkit.dot(x, x) for x in bands.values()), F.lit(0.0))).first()
    assert a == pytest.approx(b)


def test_gate_zero_is_identity(spark):
    r = spark.createDataFrame([([1.0, 2.0], [5.0, 6.0])], "x array<double>, r array<double>").select(mathkit.gated_residual(F.col("x"), F.col("r"), F.lit(0.0))).first()[0]
    assert r == [1.0, 2.0]


def test_schema_and_mixture():
    old = T.StructType([T.StructField("a", T.IntegerType()), T.StructField("b", T.StringType())])
    new = T.StructType([T.StructField("a", T.LongType()), T.StructField("c", T.StringType())])
    assert catalog.check_evolution(old, new) == [("a", "retyped"), ("b", "missing"), ("c", "added")]
    early, late = curriculum.mixture(0.0), curriculum.mixture(1.0)
    assert early[0] > early[-1] and late[-1] > late[0] and min(early + late) >= 0.02 and sum(early) == pytest.approx(1)
    assert quality.pool_adjacent([1, 3, 2, 4], [1, 1, 1, 1]) == [1, 2.5, 2.5, 4]


def test_snapshots_are_written_once(spark):
    df = spark.createDataFrame([(1, 2)], "id int, quality_tier int")
    with Scratch(spark, "t") as s:
        catalog.publish(df, s.root, 1)
        with pytest.raises(Exception):
            catalog.publish(df, s.root, 1)
            raise AssertionError


def test_components(spark):
    edges = [(1, 2), (2, 3), (9, 3), (7, 8), (5, 5), (8, 7)] + [(100 + i, 101 + i) for i in range(60)]
    with Scratch(spark, "cc") as s:
        got = dict(components(spark.createDataFrame(edges, "a long, b long"), s).collect())
        assert components(spark.createDataFrame([], "a long, b long"), s).count() == 0
    assert {got[x] for x in (1, 2, 3, 9)} == {1} and got[8] == 7 and 5 not in got and {got[100 + i] for i in range(61)} == {100}


def test_place_in_group(spark):
    rows = [(k, i, i % 5) for k in ("a", None) for i in range(300)]
    df = spark.createDataFrame(rows, "k string, i long, v long").withColumn("turn", F.md5(F.col("i").cast("string")))
    got = place_in_group(df, ["k"], "turn", ["i"], 2, value=F.col("v"), before="start").collect()
    for k in ("a", None):
        own = sorted((r for r in got if r.k == k), key=lambda r: r.turn)
        assert [r.rank0 for r in own] == list(range(300))
        assert [r.start for r in own] == [sum(x.v for x in own[:j]) for j in range(300)]


def test_modulation_starts_as_identity():
    scale, gate = mathkit.modulation(rng.normal(size=(3, 16)), rng.normal(size=(16, 8)), np.zeros((8, 10)))
    assert np.allclose(scale, 1) and np.allclose(gate, 0)


def test_truncated_normal(spark):
    r = spark.range(20_000).select(mathkit.truncated_normal(F.col("id"), 0.02, 3).alias("w")).agg(F.avg("w"), F.stddev("w"), F.max(F.abs("w"))).first()
    assert abs(r[0]) < 0.001 and abs(r[1] - 0.02 * 0.88) < 0.001 and r[2] <= 0.04


def test_maps(spark):
    df = spark.createDataFrame([([1.0] * 64,), ([float(i % 8) for i in range(64)],)], "g array<double>")
    flat, ramp = df.select(allocation.upsample(F.col("g"), 8, 3).alias("u"), allocation.gradient(F.col("g"), 8).alias("d"), allocation.gini(F.transform("g", lambda x: x + 1)).alias("q")).collect()
    assert len(flat.u) == 576 and np.allclose(flat.u, 1) and np.allclose(flat.d, 0) and abs(flat.q) < 1e-12
    assert np.allclose(ramp.u[:24], np.interp((np.arange(24) + 0.5) / 3 - 0.5, range(8), range(8))) and ramp.q > 0.2
    assert np.allclose(ramp.d[1:7], 2) and ramp.d[0] == 1


def test_render_rows(spark):
    df = spark.createDataFrame([(1, "one"), (2, "two words"), (3, "w " * 20)], "k long, t string")
    assert [r.difficulty for r in textrender.rows(df, "k", "t").orderBy("k").collect()] == ["word", "line", "paragraph"]


def test_approximate_neighbours(spark):
    """Against all pairs: of the true nearest, nine in ten are found."""
    d = "/root/testdata/sf0.01"
    e = spark.read.parquet(f"{d}/embeddings.parquet").orderBy("vec_id").toPandas()
    x = np.array(e.embedding.tolist(), dtype=float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    found = {(r.q, r.vec_id) for r in extensions.knn_lsh(spark, d).collect()}
    want = set()
    for i in np.flatnonzero(e.vec_id % 100 == 0):
        c = x @ x[i]
        c[i] = -2
        want |= {(e.vec_id[i], e.vec_id[j]) for j in np.argsort(-c)[: extensions.NEAREST]}
    assert len(want) == 25 and len(want & found) >= 0.9 * len(want)
