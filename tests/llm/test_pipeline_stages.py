"""Pipeline stages on planted rows against brute force."""

import random

import pytest

import corpus_pipeline
from assetmill.llm import overlap
from assetmill.plans.scratch import Scratch

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def grams(t):
    w = (t or "").lower().split()
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def similar(a, b):
    return 5 * len(a & b) >= 4 * len(a | b)


def groups(texts):
    sets = [grams(t) for t in texts]
    root = list(range(len(sets)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            if similar(a, sets[j]) and find(i) != find(j):
                root[max(find(i), find(j))] = min(find(i), find(j))
    return [find(i) for i in range(len(sets))]


def planted():
    rng = random.Random(5)
    words = [f"w{i}" for i in range(3000)]
    line = " ".join(rng.choice(words) for _ in range(12))
    texts = [None, "", " \n", "one", "One", "one two three"]
    for n in (9, 28, 34, 60, 130, 250, 260, 600, 2100):
        base = [rng.choice(words) for _ in range(n)]
        texts.append(" ".join(base))
        for changes in (1, 1, 2, 3, 4, 6):
            copy = list(base)
            for _ in range(max(1, changes * n // 130)):
                copy[rng.randrange(n)] = rng.choice(words)
            texts.append(" ".join(copy) if changes % 2 else " ".join(copy) + " " + line)
        texts.append(" ".join(base[: n * 85 // 100]))
    texts += [line + " " + " ".join(rng.choice(words) for _ in range(30)) for _ in range(40)]
    return texts


@pytest.mark.parametrize("block, common", [(2048, 100_000), (4, 0)])
def test_near_copies(spark, block, common):
    texts = planted()
    want = groups(texts)
    with Scratch(spark, "near") as s:
        got = dict(overlap.near_copies(spark.createDataFrame(list(enumerate(texts)), "key long, text string").repartition(3), s, block=block, most_common=common).collect())
    assert len(got) == len(texts) and len(set(want)) < len(texts) - 20
    first = {}
    for i in range(len(texts)):
        first.setdefault(got[i], i)
    assert [first[got[i]] for i in range(len(texts))] == want


def test_company_of_long_cells(monkeypatch):
    """Cells that end, go on over batches, or are too long to be held, with repeated rows."""
    import numpy as np
    import pyarrow as pa

    monkeypatch.setattr(overlap, "HELD_NODES", 6)
    rng = random.Random(3)
    rows = sorted((c, n) for c in range(12) for n in set(rng.choices(range(40), k=rng.randint(1, 30))) for _ in range(rng.randint(1, 2)))
    batches = [pa.record_batch([pa.array([r[i] for r in rows[at : at + 5]], pa.int64()) for i in (0, 1)], names=["cell", "node"]) for at in range(0, len(rows), 5)]
    got = {}
    for b in overlap._company(iter(batches)):
        for g, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            got.setdefault(g, set()).add(n)
    want = {c: {n for x, n in rows if x == c} for c in range(12)}
    assert sorted(map(sorted, got.values())) == sorted(sorted(v) for v in want.values() if len(v) > 1)
    assert any(len(v) > 6 for v in want.values()) and np.array(list(got)).dtype == np.int64


def test_stage_removes_near_copies(spark):
    texts = planted()
    rows = [(i, t, "en", "src0", len(t or "")) for i, t in enumerate(texts)]
    got = corpus_pipeline.keep_one_of_each_group(spark, spark.createDataFrame(rows, SCHEMA).repartition(3), "")
    assert sorted(r.doc_id for r in got.collect()) == sorted(set(groups(texts)))


def awkward():
    """Null and repeated ids over different texts, near copies across them, and equal rows."""
    rng = random.Random(9)
    a, b, c, d, e, f = ([f"{k}{rng.randrange(500)}" for _ in range(120)] for k in "abcdef")
    near = lambda t: " ".join([*t[:60], "changed", *t[61:]])
    rows = [(None, " ".join(a)), (None, " ".join(b)), (1, near(a)), (None, " ".join(c)), (None, " ".join(c)), (7, " ".join(d)), (7, " ".join(e)), (3, near(d)), (9, " ".join(f)), (9, near(f)), (None, None)]
    return [(i, t, "en", "src0", len(t or "")) for i, t in rows]


def test_null_and_repeated_ids(spark):
    rows = awkward()
    docs = spark.createDataFrame(rows, SCHEMA).repartition(3)
    got = [tuple(r) for r in corpus_pipeline.keep_one_of_each_group(spark, docs, "").collect()]
    want = [rows[i] for i in (1, 2, 3, 6, 7, 10)]
    assert len(got) == 7 and all(got.count(r) == 1 for r in want) and sum(r in got for r in (rows[8], rows[9])) == 1


def test_passes_of_null_and_repeated_ids(spark):
    from assetmill.llm import mixing

    rows = awkward()
    docs = spark.createDataFrame(rows, SCHEMA).repartition(3)
    with Scratch(spark, "passes") as s:
        taken = mixing.whole_passes(mixing.mix(docs, s)).count()
    got = [tuple(r) for r in corpus_pipeline.mix_sources(spark, docs, "").collect()]
    assert len(got) == taken and all(got.count(r) <= 2 * rows.count(r) for r in rows)


@pytest.mark.parametrize("stage", [corpus_pipeline.keep_known_language, corpus_pipeline.hide_secrets])
def test_row_stages_keep_rows_apart(spark, stage):
    text = "The {} was in the house and they had seen that it is good for all of us."
    rows = [(i, text.format(w), "en", "src0", len(text.format(w))) for i, w in ((None, "cat"), (None, "dog"), (7, "bird"), (7, "fish"), (7, "fish"))]
    got = [tuple(r) for r in stage(spark, spark.createDataFrame([*rows, (7, "12 34", "en", "src0", 5), (None, "12 34", "en", "src0", 5)], SCHEMA), "").collect()]
    assert sorted(map(str, got)) == sorted(map(str, rows + ([] if stage is corpus_pipeline.keep_known_language else [(7, "12 34", "en", "src0", 5), (None, "12 34", "en", "src0", 5)])))


STAGES = dict(corpus_pipeline.STAGES)
CLASHING = "_row long, row long, doc string, key long, size long, turn string, position double, gone string, text2 string"


def rough():
    """Nulls in every column, empty and very long texts, ties, repeated rows, and columns named as a stage's own."""
    rng = random.Random(12)
    words = "the of and to in a is that it was for on with as his they be at one have this".split()
    say = lambda n: " ".join(rng.choice(words) + rng.choice(["", "", "x", "ly"]) for _ in range(n))
    long = say(120_000)
    texts = [None, "", "12 34", say(30), say(60), long, say(50) + " token = abcdef123456 " + say(40), say(9)]
    rows = [(i, t, "en" if i % 3 else None, "src0" if i % 2 else None, None if t is None else len(t)) for i, t in enumerate(texts)]
    rows += [(None, say(40), None, None, None), (None, None, None, None, None), (3, say(25), "en", "src1", 1), rows[4], rows[4]]
    return [(*r, i % 2, 7, "d", 5, 6, "t", 0.5, None, "u") for i, r in enumerate(rows[:-2])] + [(*rows[4], 0, 7, "d", 5, 6, "t", 0.5, None, "u")] * 2


def test_stages_on_rough_rows(spark):
    schema = SCHEMA + ", " + CLASHING
    rows = rough()
    docs = spark.createDataFrame(rows, schema).repartition(3)
    run = lambda name, df: [tuple(r) for r in STAGES[name](spark, df, "").collect()]
    kept = run("language_id", docs)
    assert sorted(map(str, kept)) == sorted(str(r) for r in rows if r[1] and r[1] != "12 34")
    single = run("simhash_near_dedup", docs)
    assert len(single) == len(set(map(str, single))) == len(set(groups([r[1] for r in rows])))
    hidden = run("secret_scan", docs)
    assert len(hidden) == len(rows) and sum("[assign]" in (r[1] or "") for r in hidden) == 1
    plain = lambda rs: sorted(str(r[:4] + r[5:]) for r in rs if r[0] != 6)  # n_chars follows the text
    assert plain(hidden) == plain(rows) and all(r[4] == len(r[1]) for r in hidden if r[1] is not None)
    mixed = run("source_mixing", docs)
    assert {str(r) for r in mixed} <= {str(r) for r in rows if r[1]} and all(mixed.count(r) <= 2 * rows.count(r) for r in rows)
    tokens = run("bpe_tokens", docs)
    assert len(tokens) == len(rows) and sum(r[1] for r in tokens if r[0] == 5) > 100_000
    import hashlib

    assert sorted(r[3] for r in tokens) == sorted(hashlib.sha256((r[1] or "").encode()).hexdigest() for r in rows)


def test_stages_on_an_empty_table(spark):
    empty = spark.createDataFrame([], SCHEMA + ", " + CLASHING)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, empty, "")
        assert out.count() == 0 and (name == "bpe_tokens" or out.columns == empty.columns)


def test_fingerprints_find_near_copies(spark, monkeypatch):
    """The stage's groups come by SimHash: near copies still meet where the second search finds nothing."""
    monkeypatch.setattr(overlap, "_near_bits", lambda n, payloads: iter(()))
    rng = random.Random(4)
    base = [rng.choice([f"v{i}" for i in range(900)]) for _ in range(1500)]
    texts = [" ".join(base), " ".join([*base[:700], "other", *base[701:]]), " ".join(base[:-1]), "again and again", " ".join(base[:300])]
    rows = [(i, t, "en", "src0", len(t)) for i, t in enumerate(texts)]
    got = corpus_pipeline.keep_one_of_each_group(spark, spark.createDataFrame(rows, SCHEMA).repartition(3), "")
    assert sorted(r.doc_id for r in got.collect()) == sorted(set(groups(texts))) == [0, 3, 4]
