"""Routing traces over whole tables."""

import os

import pandas as pd

from assetmill import workloads

SF = "/root/testdata/sf0.001"


def test_trace_covers_every_token(spark):
    got = workloads.queries()["w27_diversity"](spark, SF).toPandas()
    assert len(got) == spark.read.parquet(f"{SF}/embeddings.parquet").count()


def test_allocation_counts_claims(spark, tmp_path):
    """All 29 layers and 50 steps by brute force, on labels of 11, 5 and 1 vectors."""
    import math

    import numpy as np

    from assetmill.operators import routing

    rng = np.random.default_rng(3)
    rows = [(i, rng.normal(size=64).astype("float32").tolist(), 0 if i < 11 else 1 if i < 16 else 2) for i in range(17)]
    rows[4] = (4, rows[3][1], 0)
    os.makedirs(tmp_path / "sf")
    pd.DataFrame(rows, columns=["vec_id", "embedding", "label"]).to_parquet(tmp_path / "sf" / "embeddings.parquet")
    want, layers = {}, range(3, 32)
    for label in range(3):
        own = [r for r in rows if r[2] == label]
        count = np.zeros(len(own))
        for layer in layers:
            w = np.array([[routing.weight(i, e, layer) for e in range(8)] for i in range(64)])
            cap = math.ceil((4 if layer in (3, 4) else 2) * len(own) / 8)
            for step in range(50):
                s = 1 - step / 49
                z = np.array([np.round((1 - s) * np.array(r[1]) + s * ((np.arange(64) * 7919 + r[0] * 104729) % 1009 / 1009 - 0.5), 9) for r in own]) @ w
                p = np.exp(z - z.max(axis=1, keepdims=True))
                p = np.round(p / p.sum(axis=1, keepdims=True), 9)
                for e in range(8):
                    for at in sorted(range(len(own)), key=lambda k: (-p[k, e], k))[:cap]:
                        count[at] += 1
        span = count.max() - count.min()
        want |= {(label, i): float(round((c - count.min()) / span, 4)) if span else 0.0 for i, c in enumerate(count)}
    got = {(r["sample"], r["pos"]): r["share"] for r in workloads.queries()["w27_allocation"](spark, str(tmp_path / "sf")).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) <= 2e-4 for k in want)


def test_allocation_shuffles_no_scores(spark, monkeypatch):
    """A token leaves as one row for each part of the steps and layers, and parts change no result."""
    from assetmill.workloads import evaluation

    whole = evaluation.claims(spark, SF).groupBy("sample", "pos").sum("c")
    want = {tuple(r) for r in whole.collect()}
    monkeypatch.setattr(evaluation, "HELD_TOKENS", 10)
    parts = evaluation.claims(spark, SF)
    assert evaluation.claims(spark, SF).count() < 29 * 50 * len(want) and {tuple(r) for r in parts.groupBy("sample", "pos").sum("c").collect()} == want
