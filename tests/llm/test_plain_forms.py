"""Operators against plain versions of their methods, written apart from them."""

import hashlib
import math
import random
import zlib

import numpy as np
import pytest

from assetmill.llm import digest, language, sharding, toxicity
from assetmill.plans.scratch import Scratch

SF = "/root/testdata/sf0.01"


def test_ftrl_against_a_plain_loop():
    """One coordinate at a time, with dictionaries."""
    rng = random.Random(1)
    rows = [(np.unique(np.array(rng.choices(range(60), k=rng.randint(1, 12)))), rng.randint(0, 1)) for _ in range(150)]
    z, n = {}, {}

    def weight(i):
        v = z.get(i, 0.0)
        if abs(v) <= toxicity.L1:
            return 0.0
        return -(v - math.copysign(toxicity.L1, v)) / ((toxicity.BETA + math.sqrt(n.get(i, 0.0))) / toxicity.ALPHA + toxicity.L2)

    for _ in range(toxicity.EPOCHS):
        for cells, label in rows:
            at = [*cells.tolist(), "bias"]
            p = 1 / (1 + math.exp(-sum(map(weight, at))))
            old = {i: weight(i) for i in at}
            for i in at:
                g = p - label
                sigma = (math.sqrt(n.get(i, 0.0) + g * g) - math.sqrt(n.get(i, 0.0))) / toxicity.ALPHA
                z[i] = z.get(i, 0.0) + g - sigma * old[i]
                n[i] = n.get(i, 0.0) + g * g
    w, bias = toxicity.train(rows)
    assert bias == pytest.approx(weight("bias"), abs=1e-9)
    assert all(w[i] == pytest.approx(weight(i), abs=1e-6) for i in range(60)) and any(w[:60]) and not w[60:].any()


def test_toxicity_features_are_words_pairs_and_skips():
    def cells(text):
        words = [zlib.crc32(w.encode()) * 0x9E3779B97F4A7C15 % 2**64 for w in text.split()]
        out = set(words)
        for gap, salt in ((1, 0xC2B2AE3D27D4EB4F), (2, 0x165667B19E3779F9)):
            out |= {(a * 3 + b * salt) * 0x9FB21C651E98DF25 % 2**64 for a, b in zip(words, words[gap:])}
        return {x >> 44 for x in out}

    text = "you are a bad bad word and you know it"
    assert set(toxicity.Features()(text.upper().encode()).tolist()) == cells(text)


def plain_digest(buf):
    """Counts by loops over windows of five bytes, quartiles by sorting."""
    mix, salt = digest._MIX.tolist(), digest._SALT.tolist()
    counts = [0] * digest.BUCKETS
    for (j, k), s in zip(digest.TRIPLETS, salt):
        for i in range(len(buf) - k if len(buf) >= 3 else 0):
            h = (mix[0][buf[i]] + mix[1][buf[i + j]]) % 2**32 ^ (mix[2][buf[i + k]] + s) % 2**32
            counts[(h * 0x9E3779B1 % 2**32) >> 24] += 1
    ranked = sorted(counts)
    q = [ranked[63], ranked[127], ranked[191]]
    codes = [sum(c > x for x in q) for c in counts]
    body = "".join(f"{codes[i] * 64 + codes[i + 1] * 16 + codes[i + 2] * 4 + codes[i + 3]:02x}" for i in range(0, 256, 4))
    return f"{int(math.log(len(buf) + 1) / math.log(1.3)) % 256:02x}{q[0] * 15 // q[2] if q[2] else 0:x}{q[1] * 15 // q[2] if q[2] else 0:x}{body}"


@pytest.mark.parametrize("text", ["", "ab", "abc", "abcde", "the quick brown fox " * 40, "é日本" * 50, "a" * 3000])
def test_digest_against_loops(text):
    assert digest.to_text(digest.digest(text.encode())) == plain_digest(text.encode())


def test_short_texts_do_not_look_alike():
    d = lambda t: digest.digest(t.encode())
    assert digest.likeness(d("w w w w"), d("")) < 0.5 and digest.likeness(d(""), d("")) == 1.0
    assert digest.likeness(d("hello there"), d("12 34 56 78")) < 0.6
    long = "in the house they had seen that it is good for all of us and more so " * 30
    assert digest.likeness(d(long), d(long + " x")) > 0.9


def test_next_of_an_id_with_most_rows(spark):
    """An id that half of all rows share is many ranges; null ids come last."""
    rng = random.Random(6)
    rows = [(7, f"text {i} " + "ab" * rng.randint(0, 30)) for i in range(60)] + [(i * 3, f"other {i}") for i in range(30)] + [(None, f"null {i}") for i in range(10)] + [(7, "text 1"), (7, "text 1")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = digest.edited_likeness(df, 8)
    from pyspark.sql import functions as F

    turns = {r.text: r.turn for r in df.select("text", F.shiftrightunsigned(F.xxhash64(F.col("text").cast("binary")), 1).alias("turn")).distinct().collect()}
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), turns[r[1]], r[1]))
    want = []
    for (i, t), (_, nxt) in zip(order, order[1:] + order[:1]):
        half = len(t) // 2
        want.append((i, len(t), hashlib.sha256((t[: len(t) - half] + nxt[:half]).encode()).hexdigest()))
    have = [(r.doc_id, r.n_chars, r.edited_sha256) for r in got.collect()]
    assert sorted(map(str, have)) == sorted(map(str, want))
    used = got.select(F.spark_partition_id().alias("p"), "doc_id").where("doc_id = 7").select("p").distinct().count()
    assert used > 2


def walk(key, tree):
    """The shard of a key by recursion over the tree."""
    weight = lambda x: 1 if isinstance(x, int) else sum(map(weight, x))

    def down(path, node):
        if isinstance(node, int):
            return node
        best = []
        for i, child in enumerate(node):
            name = f"s{child}" if isinstance(child, int) else f"{path}.{i}"
            u = (int(hashlib.md5(f"{key}/{name}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52
            best.append((-math.log(u) / weight(child), i, name, child))
        _, _, name, child = min(best)
        return down(name, child)

    return down("t", tree.regions)


def test_shards_by_a_plain_walk(spark):
    with Scratch(spark, "walk") as s:
        got = sharding.shard(spark.createDataFrame([(i, f"t{i}") for i in range(300)] + [(None, None)], "doc_id long, text string"), s).collect()
    for r in got:
        key = "null" if r.doc_id is None else str(r.doc_id)
        assert r.shard == walk(key, sharding.LAYOUT) and r.grown_shard == walk(key, sharding.LAYOUT.grown())


def test_a_heavier_rack_moves_rows_inside_its_region_and_into_it():
    """One more shard in a rack: its region only gains rows, and inside the region only its rack and, there, the new
    shard do."""
    tree = sharding.Tree((((0, 1), (2, 3)), ((4, 5), (6, 7))))
    more = sharding.Tree((((0, 1, 8), (2, 3)), ((4, 5), (6, 7))))
    rack = {0: "a", 1: "a", 8: "a", 2: "b", 3: "b", 4: "c", 5: "c", 6: "d", 7: "d"}
    moved = 0
    for i in range(4000):
        x, y = walk(str(i), tree), walk(str(i), more)
        if x != y:
            moved += 1
            assert rack[y] in "ab"
            assert rack[x] in "cd" or (rack[y] == "a" and (rack[x] == "b" or y == 8))
    assert moved > 300


def test_language_on_rows_held_out(spark):
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    model = language.fit(docs.where(~held))
    with Scratch(spark, "held") as s:
        got = language.identify(docs.where(held), s, model=model).join(docs.select("doc_id", F.col("lang").alias("want")), "doc_id").collect()
    assert len(got) > 100 and sum(r.lang == r.want for r in got) / len(got) > 0.97


def test_more_languages_than_the_bound(spark):
    docs = spark.createDataFrame([(i, f"text number {i}", f"l{i}") for i in range(language.MOST_LANGUAGES * 5)], "doc_id long, text string, lang string")
    with pytest.raises(Exception, match="languages"):
        language.fit(docs)
