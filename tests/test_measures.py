"""Queries without a SQL twin, and what plans and operators promise beyond rows."""

import math
import random

import numpy as np
import pytest

from assetmill import workloads
from assetmill.operators import components, curriculum, dedup, mathkit, quality
from assetmill.plans.scratch import Scratch

SF = "/root/testdata/sf0.001"


def rows(spark, name):
    return workloads.queries()[name](spark, SF).collect()


def test_bands_find_what_brute_force_finds(spark):
    (r,) = rows(spark, "w04_banded_recall")
    assert r.brute_pairs == r.banded_pairs > 0


def test_near_bits_lose_nothing(spark):
    rng = random.Random(2)
    base = [rng.getrandbits(64) for _ in range(30)]
    prints = base + [b ^ sum(1 << k for k in rng.sample(range(64), rng.randint(0, 5))) for b in base for _ in range(4)]
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    got = dedup.near_bits(spark.createDataFrame(list(enumerate(signed)), "vec_id long, fp long")).collect()
    first = {}
    for i, p in enumerate(signed):
        first.setdefault(p, i)
    want = {(a, b, (prints[a] ^ prints[b]).bit_count()) for a in first.values() for b in first.values() if a < b and (prints[a] ^ prints[b]).bit_count() <= 3}
    assert {tuple(r) for r in got} == want and len(got) == len(want) > 30


def texts():
    rng = random.Random(8)
    line = " ".join(f"s{k}" for k in range(40))
    out = [None, "", "one", "ONE", "one two"]
    for n in (6, 20, 60, 200):
        base = [f"w{rng.randrange(900)}" for _ in range(n)]
        out.append(" ".join(base))
        for k in (1, 1, 2, 5):
            copy = list(base)
            copy[rng.randrange(n)] = "changed"
            out.append(" ".join(copy * k) if k == 5 else " ".join(copy[: n - k]))
    return out + [f"{line} " + " ".join(f"z{rng.randrange(900)}" for _ in range(30)) for _ in range(60)]


def test_near_sets_against_all_pairs(spark):
    """Also with a passage that more texts share than the order lets stand in front."""
    t = texts()
    grams = [{" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if (w := (x or "").lower().split()) else set() for x in t]
    with Scratch(spark, "sets") as s:
        sets = s.keep(dedup.shingle_sets(spark.createDataFrame(list(enumerate(t)), "doc_id long, text string")), "sets")
        got = {(r.a, r.b) for r in dedup.near_sets(dedup.set_nodes(sets)).collect()}
        names = dict(dedup.set_names(sets).collect())
    first = {i: min(j for j in range(len(t)) if grams[j] == grams[i]) for i in range(len(t))}
    assert names == first
    nodes = sorted(set(first.values()))
    want = {(a, b) for a in nodes for b in nodes if a < b and grams[a] and 5 * len(grams[a] & grams[b]) >= 4 * len(grams[a] | grams[b])}
    assert got == want and len(want) > 5


@pytest.mark.parametrize("large", [2, 500])
def test_spread_of_large_groups(spark, monkeypatch, large):
    monkeypatch.setattr(components, "LARGE_GROUP", large)
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(i, i % 7 if i < 30 else 9, i * 3 % 11) for i in range(60)], "id long, g long, v long")
    got = {r.id: (r.g, r.v, r.low) for r in components.spread(df, "g", F.min("v"), "low").collect()}
    every = [(i, i % 7 if i < 30 else 9, i * 3 % 11) for i in range(60)]
    assert got == {i: (g, v, min(x for _, h, x in every if h == g)) for i, g, v in every}


def test_quantile_tiers_and_buckets(spark):
    rng = random.Random(5)
    data = [(i, rng.choice([0.0, 2.5, 5.0, rng.random() * 10]), "a" if i % 4 else None) for i in range(203)]
    df = spark.createDataFrame(data, "doc_id long, s double, stream string")
    got = {r.doc_id: r.tier for r in quality.tier_quantile(df, "s", "stream", "doc_id").collect()}
    for stream in ("a", None):
        own = sorted((s, i) for i, s, x in data if x == stream)
        n, each = len(own), [len(own) // 5 + (k < len(own) % 5) for k in range(5)]
        want = [k + 1 for k in range(5) for _ in range(each[k])]
        assert len(want) == n and [got[i] for _, i in own] == want
    part = spark.createDataFrame([(i, float(round(s))) for i, s, _ in data], "doc_id long, s double")
    have = {r.doc_id: r.episodic_bucket for r in curriculum.buckets(part, "s", "doc_id").collect()}
    ranked = sorted((float(round(s)), i) for i, s, _ in data)
    assert [have[i] for _, i in ranked] == [k * 8 // len(ranked) + 1 for k in range(len(ranked))]


def test_assigned_crops_keep_most(spark):
    sizes = curriculum.crops(512)
    boxes = [(w, h) for w in (1, 64, 100, 333, 640, 1024, 5000) for h in (1, 64, 128, 500, 1000, 4096)]
    got = {(r.width, r.height): (r.crop_w, r.crop_h) for r in curriculum.assign_crop(spark.createDataFrame(boxes, "width int, height int"), sizes).collect()}
    for w, h in boxes:
        keep = lambda c: round(min(c[0] / c[1] / (w / h), w / h / (c[0] / c[1])), 9)
        assert got[w, h] == max(sizes, key=lambda c: (keep(c), c[0] * c[1], -c[0]))


def test_isotonic_labels_rise(spark):
    pooled = [r.pooled for r in rows(spark, "w05_calibration_isotonic")]
    assert pooled == sorted(pooled)


def test_steady_routing_by_variant(spark):
    """A router of the content alone never changes its mind; on unit vectors the time step itself moves the other two."""
    steady = {r["mode"]: r.steady for r in rows(spark, "w15_collapse")}
    assert steady["content"] == 1.0 and 0 < steady["modulated"] < 1 and 0 < steady["decoupled"] < 1


def test_split_steps_keep_small_parts(spark):
    got = {(r.part, r.kind): r for r in rows(spark, "w20_split_optimizer")}
    assert all(abs(got[p, "split"].smallest - 1) < 1e-3 and abs(got[p, "split"].largest - 1) < 1e-3 for p in "qkv")
    assert all(got[p, "fused"].largest <= 1.001 for p in "qkv")


def test_momentum_steps_have_one_size(spark):
    assert all(abs(r.step_rms - 0.2) < 0.01 for r in rows(spark, "w20_momentum_steps"))


def test_late_rows_are_counted(spark):
    (r,) = rows(spark, "st_late_rows")
    assert r.on_time == 0 and r.late > 0


def test_norms(spark):
    from pyspark.sql import functions as F

    x = np.random.default_rng(1).normal(size=64)
    df = spark.createDataFrame([(x.tolist(),)], "x array<double>")
    r = df.select(mathkit.rms_norm(F.col("x")).alias("a"), mathkit.layer_norm(F.col("x")).alias("b")).first()
    assert np.allclose(r.a, x / math.sqrt((x**2).mean() + 1e-6)) and np.allclose(r.b, (x - x.mean()) / math.sqrt(x.var() + 1e-6))


def test_cheap_tiers_go_before_python(spark, capsys):
    """A predicate on columns is evaluated below a Python function, so its rows never reach it."""
    from pyspark.sql import functions as F

    from assetmill.operators import validate
    from assetmill.workloads.curation import assets

    slow = F.udf(lambda t: bool(t), "boolean")
    validate.run_tiers(assets(spark, SF), [slow(F.col("text")), F.col("doc_id") > 5]).select("doc_id").explain("formatted")
    plan = capsys.readouterr().out
    assert "BatchEvalPython" in plan and "GreaterThan(doc_id,5)" in plan


def test_bucketed_join_has_no_exchange_of_its_sides(spark, capsys):
    workloads.queries()["sink_bucketed"](spark, SF).explain()
    plan = capsys.readouterr().out
    assert "SortMergeJoin" in plan and "hashpartitioning(o_orderkey" not in plan and "hashpartitioning(l_orderkey" not in plan


def test_partition_is_pruned(spark, capsys):
    workloads.queries()["op_partition_prune"](spark, SF).explain()
    assert "PartitionFilters: [isnotnull(quality_tier" in capsys.readouterr().out
