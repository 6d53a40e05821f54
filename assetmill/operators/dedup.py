"""Exact and near-duplicate removal on fingerprints."""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from assetmill.operators.validate import dct_basis
from assetmill.plans.ship import ship


def exact(df: DataFrame, key: str, order: list[Column]) -> DataFrame:
    """One row id per key, the first by ``order``; partial aggregation, no sort of payloads."""
    return df.groupBy(key).agg(F.min_by("doc_id", F.struct(*order)).alias("keep_id"), F.count(F.lit(1)).alias("copies"))


def representative(members: DataFrame) -> DataFrame:
    """One id per cluster: the largest area, then the best tier, then the smallest id."""
    best = F.struct(F.col("width") * F.col("height"), "quality_tier", -F.col("doc_id"))
    return members.groupBy("cluster").agg(F.max_by("doc_id", best).alias("keep_id"), F.count(F.lit(1)).alias("members"))


def ahash(grid: Column) -> Column:
    """Bits of cells above their mean, as text."""
    m = F.aggregate(grid, F.lit(0.0), lambda s, x: s + x) / F.size(grid)
    return F.array_join(F.transform(grid, lambda x: F.when(x > m, F.lit("1")).otherwise(F.lit("0"))), "")


def phash(grid: Column, side: int = 8) -> Column:
    """Signs of the cosine coefficients against their median, as text of bits. Coefficients are rounded so
    that ties fall alike everywhere."""
    b = dct_basis(side)
    basis = F.array(*(F.array(*(F.lit(b[v][r] * b[u][c]) for r in range(side) for c in range(side))) for v in range(side) for u in range(side)))
    flat = F.transform(basis, lambda row: F.round(F.aggregate(F.zip_with(grid, row, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x), 9))
    ranked = F.array_sort(flat)
    median = (F.get(ranked, F.lit(side * side // 2 - 1)) + F.get(ranked, F.lit(side * side // 2))) / 2
    return F.array_join(F.transform(flat, lambda x: F.when(x > median, F.lit("1")).otherwise(F.lit("0"))), "")


def phash_column(df: DataFrame, grid: str, name: str = "bits") -> DataFrame:
    """``phash`` by an Arrow kernel, one matrix product a batch, for whole tables."""
    b = np.array(dct_basis())
    basis = np.kron(b, b).T
    schema = T.StructType([*df.schema.fields, T.StructField(name, T.StringType())])

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.round(np.array(batch.column(df_at).to_pylist(), dtype=np.float64) @ basis, 9)
            bits = (x > np.median(x, axis=1, keepdims=True)).astype(np.uint8) + 48
            yield pa.record_batch([*batch.columns, pa.array([r.tobytes().decode() for r in bits])], names=[*batch.schema.names, name])

    df_at = df.columns.index(grid)
    return df.mapInArrow(run, schema)


# --- texts: word shingles ---------------------------------------------------------------------------

#: Words of a shingle, and the least Jaccard similarity of near copies as a fraction.
SHINGLE, NEAR = 5, (4, 5)
#: A shingle that stands in the prefixes of more texts than this goes behind all others in the order, and how many
#: such shingles are told apart, the most frequent first.
OFTEN, MOST_OFTEN = 32, 100_000
_WORDS = re.compile(rb"[^\x20\x09-\x0D]+")
#: Word hashes that a task remembers.
KNOWN_WORDS = 200_000


def _shingle_hashes(words: list[bytes], size: int, known: dict[bytes, int]) -> np.ndarray:
    """Sorted distinct hashes of the runs of ``size`` words, from hashes of the words."""
    from hashlib import blake2b

    if not words:
        return np.zeros(0, dtype=np.int64)
    if len(known) > KNOWN_WORDS:
        known.clear()
    ids = []
    for w in words:
        h = known.get(w)
        if h is None:
            h = known[w] = int.from_bytes(blake2b(w, digest_size=8).digest(), "little")
        ids.append(h)
    x = np.array(ids, dtype=np.uint64)
    n = max(1, len(x) - size + 1)
    total = np.full(n, min(len(x), size), dtype=np.uint64)
    for k in range(min(size, len(x))):
        total = (total + x[k : k + n]) * np.uint64(0x9E3779B97F4A7C15)
        total ^= total >> np.uint64(29)
    return np.unique((total * np.uint64(0xBF58476D1CE4E5B9)).view(np.int64))


def shingle_sets(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """doc_id, set (sorted hashes of the distinct shingles of words) and n, its size. Words lie between spaces and
    the controls 9 to 13, A-Z is lower-cased; fewer words than ``size`` are one shingle, none or null an empty set."""
    ship(docs.sparkSession)

    def run(batches):
        import pyarrow as pa

        known: dict[bytes, int] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                ids, texts = batch.slice(at, 512).columns
                sets = [_shingle_hashes(_WORDS.findall(t.as_buffer().to_pybytes().lower()), size, known) for t in texts]
                yield pa.record_batch([ids, pa.array(sets, pa.list_(pa.int64())), pa.array(list(map(len, sets)), pa.int32())], names=["doc_id", "set", "n"])

    return docs.select("doc_id", F.coalesce("text", F.lit("")).cast("binary").alias("t")).mapInArrow(run, "doc_id long, set array<long>, n int")


def set_nodes(sets: DataFrame) -> DataFrame:
    """node (smallest doc_id), n and set of each different set; equal sets are one node."""
    firsts = sets.groupBy(F.xxhash64("set").alias("_h"), F.hash("set").alias("_g"), "n").agg(F.min("doc_id").alias("node")).select("node")
    return firsts.join(sets, F.col("node") == F.col("doc_id")).select("node", "n", "set")


def set_names(sets: DataFrame) -> DataFrame:
    """doc_id and the node that its set belongs to; a window-free join on the set's hashes."""
    keys = (F.xxhash64("set").alias("_h"), F.hash("set").alias("_g"), "n")
    own = sets.select("doc_id", *keys)
    names = own.groupBy("_h", "_g", "n").agg(F.min("doc_id").alias("node"))
    return own.join(names, ["_h", "_g", "n"]).select("doc_id", "node")


def near_sets(nodes: DataFrame, near: tuple[int, int] = NEAR) -> DataFrame:
    """Pairs (a, b, shared, jaccard) of nodes whose sets have a Jaccard similarity of ``near`` or more, none missed.

    In any order of all shingles two such sets meet in their first n - ceil(n * near) + 1 ones, so an equi-join on
    these gives all candidates. The order is by hash, with shingles that are frequent there put last, which keeps
    passages that many texts share from making candidates. Each candidate is checked on the whole sets.
    """
    up, down = near
    most = lambda n: n - F.floor((up * n + down - 1) / down) + 1
    some = nodes.where("n > 0")
    seen = some.select(F.explode(F.slice("set", F.lit(1), most(F.col("n")).cast("int"))).alias("s")).groupBy("s").count()
    late = np.sort(seen.where(F.col("count") > OFTEN).orderBy(F.desc("count"), "s").limit(MOST_OFTEN).select("s").toPandas()["s"].to_numpy(dtype=np.int64))
    ship(nodes.sparkSession)

    def first(batches):
        import pyarrow as pa

        for batch in batches:
            node, n, cell = [], [], []
            for i, k, own in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                h = own.values.to_numpy()
                often = np.isin(h, late, assume_unique=True) if len(late) else np.zeros(k, dtype=bool)
                cell.append(np.concatenate([h[~often], h[often]])[: k - (up * k + down - 1) // down + 1])
                node.append(np.full(len(cell[-1]), i))
                n.append(np.full(len(cell[-1]), k, dtype=np.int32))
            if node:
                yield pa.record_batch([pa.array(np.concatenate(node)), pa.array(np.concatenate(n)), pa.array(np.concatenate(cell))], names=["node", "n", "cell"])

    cells = some.select("node", "n", "set").mapInArrow(first, "node long, n int, cell long")
    a, b = cells.alias("a"), cells.alias("b")
    sizes = (up * F.col("a.n") <= down * F.col("b.n")) & (up * F.col("b.n") <= down * F.col("a.n"))
    pairs = a.join(b, (F.col("a.cell") == F.col("b.cell")) & (F.col("a.node") < F.col("b.node")) & sizes).select(F.col("a.node").alias("a"), F.col("b.node").alias("b")).distinct()
    x, y = (nodes.select(F.col("node").alias(k), F.col("n").alias(f"n{k}"), F.col("set").alias(f"s{k}")) for k in "ab")
    both = pairs.join(x, "a").join(y, "b").withColumn("shared", F.size(F.array_intersect("sa", "sb")))
    union = F.col("na") + F.col("nb") - F.col("shared")
    return both.where(down * F.col("shared") >= up * union).select("a", "b", "shared", F.round(F.col("shared") / union, 6).alias("jaccard"))


def star_clusters(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """Without transitivity: each node goes to its best smaller neighbour (most alike, then smallest), or stays."""
    best = pairs.groupBy(F.col("b").alias("node")).agg(F.max_by("a", F.struct("jaccard", -F.col("a"))).alias("_to"))
    return nodes.select("node").join(best, "node", "left").select("node", F.coalesce("_to", "node").alias("centre"))


def two_stage(members: DataFrame, names: DataFrame, clusters: DataFrame) -> DataFrame:
    """Exact copies first, by ``sha256``, then near copies among what is left: doc_id and stage (exact, near or kept)
    of each row of ``members`` (doc_id, sha256, width, height, quality_tier). ``names`` maps doc_id to node and
    ``clusters`` node to cluster, where it has more than itself. The best by area, tier and smallest id stays."""
    best = F.struct(F.col("width") * F.col("height"), "quality_tier", -F.col("doc_id"))
    one = members.groupBy("sha256").agg(F.max_by("doc_id", best).alias("keep"))
    left = members.join(one.select(F.col("keep").alias("doc_id")), "doc_id", "left_semi")
    grouped = left.join(names, "doc_id").join(clusters, "node", "left").withColumn("cluster", F.coalesce("cluster", "node"))
    stay = representative(grouped).select(F.col("keep_id").alias("doc_id"), F.lit("kept").alias("_near"))
    after = left.select("doc_id").join(stay, "doc_id", "left").select("doc_id", F.coalesce("_near", F.lit("near")).alias("_stage"))
    return members.select("doc_id").join(after, "doc_id", "left").select("doc_id", F.coalesce("_stage", F.lit("exact")).alias("stage"))


# --- grids: bits -------------------------------------------------------------------------------------


def bits_number(bits: Column) -> Column:
    """64 bits as text of 0 and 1, as one long."""
    half = lambda at: F.conv(F.substring(bits, at, 32), 2, 10).cast("long")
    return F.shiftleft(half(1), 32).bitwiseOR(half(33))


def hamming(a: Column, b: Column) -> Column:
    """Differing bits of two longs."""
    return F.bit_count(a.bitwiseXOR(b)).cast("int")


def near_bits(prints: DataFrame, radius: int = 3) -> DataFrame:
    """Pairs of ids within ``radius`` of the 64 bits of ``fp``. Of the radius + 3 bands, two fingerprints that close
    agree in three at least, so an equi-join on triples of bands loses nothing and meets few others. Equal
    fingerprints are one node: the ids are the smallest of each."""
    from itertools import combinations

    nodes = prints.groupBy("fp").agg(F.min("vec_id").alias("id"))
    n, edges = radius + 3, [64 * i // (radius + 3) for i in range(radius + 4)]
    mask = lambda i: sum(1 << b for b in range(edges[i], edges[i + 1]))
    masks = [sum(mask(i) for i in three) for three in combinations(range(n), 3)]
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    keyed = nodes.select("id", "fp", F.posexplode(F.array(*(F.col("fp").bitwiseAND(F.lit(signed(m))) for m in masks))).alias("band", "key"))
    a, b = keyed.alias("a"), keyed.alias("b")
    apart = hamming(F.col("a.fp"), F.col("b.fp"))
    return a.join(b, (F.col("a.band") == F.col("b.band")) & (F.col("a.key") == F.col("b.key")) & (F.col("a.id") < F.col("b.id")) & (apart <= radius)).select(F.col("a.id").alias("a"), F.col("b.id").alias("b"), apart.alias("bits_apart")).distinct()


def near_bits_brute(queries: DataFrame, prints: DataFrame, radius: int = 3) -> DataFrame:
    """Baseline: a stated set of queries against all fingerprints, both with vec_id and fp."""
    q = queries.select(F.col("vec_id").alias("q"), F.col("fp").alias("qfp"))
    apart = hamming(F.col("qfp"), F.col("fp"))
    return prints.join(q, (apart <= radius) & (F.col("q") != F.col("vec_id"))).select("q", "vec_id", apart.alias("bits_apart"))
