"""Document fingerprints: a locality-sensitive digest of byte triplets by bucket quartiles.

Every window of five bytes gives six triplets that contain its first byte; each triplet is hashed to
one of 256 buckets. A bucket's code is the quartile (0 to 3) of its count among all buckets, which
makes the body; the header holds the length on a logarithmic scale and the ratios of the quartiles.
Two digests are compared with a difference score that has a largest value, so likeness is 0 to 1.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assetmill.llm.batches import arrow_schema, raw_text, tidy
from assetmill.plans.ship import ship

BUCKETS = 256
#: Offsets of the second and third byte of the six triplets, and a salt for each.
TRIPLETS = ((1, 2), (1, 3), (2, 3), (1, 4), (2, 4), (3, 4))
LENGTH_STEP = math.log(1.3)
#: What a difference in code, length step and ratio step costs, and the most the header can cost.
CODE_COST = np.array([0, 1, 2, 6], dtype=np.int64)
LENGTH_COST, LENGTH_MOST, RATIO_COST, RATIO_MOST = 4, 48, 4, 32
MOST = int(CODE_COST[-1]) * BUCKETS + LENGTH_MOST + 2 * RATIO_MOST
#: Differences beyond this share of the largest are as good as unrelated.
SPAN = 0.5

_rng = np.random.Generator(np.random.PCG64(20))
_MIX = _rng.integers(0, 1 << 32, size=(3, 256), dtype=np.uint32)
_SALT = _rng.integers(0, 1 << 32, size=len(TRIPLETS), dtype=np.uint32)


def bucket_counts(buf: bytes) -> np.ndarray:
    b = np.frombuffer(buf, dtype=np.uint8)
    counts = np.zeros(BUCKETS, dtype=np.int64)
    if len(b) < 3:
        return counts
    x, y, z = (_MIX[i][b] for i in range(3))
    for (j, k), salt in zip(TRIPLETS, _SALT):
        n = len(b) - k
        if n > 0:
            h = x[:n] + y[j : j + n]
            h ^= z[k : k + n] + salt
            h *= np.uint32(0x9E3779B1)
            h >>= np.uint32(24)
            counts += np.bincount(h.astype(np.intp), minlength=BUCKETS)
    return counts


def digest(buf: bytes) -> tuple[np.ndarray, int, int, int]:
    """Codes of the buckets, length step, and two ratio steps (0 to 15)."""
    counts = bucket_counts(buf)
    ranked = np.sort(counts)
    q1, q2, q3 = (int(ranked[BUCKETS * i // 4 - 1]) for i in (1, 2, 3))
    codes = (counts > q1).astype(np.int8) + (counts > q2) + (counts > q3)
    step = int(math.log(len(buf) + 1) / LENGTH_STEP) & 0xFF
    return codes, step, q1 * 15 // q3 if q3 else 0, q2 * 15 // q3 if q3 else 0


def to_text(d: tuple[np.ndarray, int, int, int]) -> str:
    codes, step, r1, r2 = d
    packed = codes.reshape(-1, 4) @ np.array([64, 16, 4, 1])
    return f"{step:02x}{r1:x}{r2:x}" + packed.astype(np.uint8).tobytes().hex()


def from_text(text: str) -> tuple[np.ndarray, int, int, int]:
    packed = np.frombuffer(bytes.fromhex(text[4:]), dtype=np.uint8)
    codes = np.stack([packed >> 6, packed >> 4 & 3, packed >> 2 & 3, packed & 3], axis=1).reshape(-1).astype(np.int8)
    return codes, int(text[:2], 16), int(text[2], 16), int(text[3], 16)


def difference(a, b) -> int:
    """0 for equal digests, at most ``MOST``."""
    body = int(CODE_COST[np.abs(a[0] - b[0])].sum())
    return body + min(LENGTH_MOST, LENGTH_COST * abs(a[1] - b[1])) + sum(min(RATIO_MOST, RATIO_COST * abs(p - q)) for p, q in zip(a[2:], b[2:]))


def likeness(a, b) -> float:
    """1 for equal digests, 0 from half of the largest difference on. Texts that fill few buckets can only differ in
    these, so the body counts against what both fill, if that is less."""
    body = min(SPAN * int(CODE_COST[-1]) * BUCKETS, float(CODE_COST[a[0]].sum() + CODE_COST[b[0]].sum()))
    return max(0.0, 1.0 - difference(a, b) / (body + SPAN * (LENGTH_MOST + 2 * RATIO_MOST)))


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id and fingerprint of every whole text."""
    from assetmill.llm.batches import map_rows

    return map_rows(docs.select("doc_id", raw_text()), lambda: lambda i, buf: (i, to_text(digest(buf))), "doc_id long, fingerprint string")


def edited_likeness(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """Fingerprints of all texts, of their edited texts, and how alike they are.

    In descending doc_id each text has a next one, the last text's is the first. The edited text has its
    last floor(n_chars/2) code points replaced by the first as many (or all) of the next text. Columns:
    doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    Texts are moved once, into ranges of doc_id cut at quantiles, and of a hash of the text inside an id that several
    quantiles fall on; the first rows of a range go to the range before as well, so that every row meets its next
    one inside one sorted partition. Null texts count as empty, null ids come last, rows with the same id stand by a
    hash of their text; one row is its own next; an empty table gives no rows. Other columns are not read.
    """
    spark = docs.sparkSession
    ship(spark)
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    low = -(1 << 63)
    text = raw_text()
    own = docs.select("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(low)).alias("at"), F.shiftrightunsigned(F.xxhash64(text), 1).alias("turn"), text.alias("text"))
    found: list[int] = []
    if parts > 1:
        found = own.agg(F.percentile_approx("at", F.array(*(F.lit(i / parts) for i in range(1, parts))), F.lit(max(10_000, 20 * parts))).alias("c")).first()["c"] or []
    cuts = sorted(set(found), reverse=True)
    n = len(cuts)
    shares = [found.count(c) for c in cuts]  # an id that several quantiles fall on gets as many ranges
    base = [i + sum(shares[:i]) - i for i in range(n + 1)]
    total = base[-1] + 1
    longs = lambda xs: F.array(*(F.lit(x).cast("long") for x in xs)) if xs else F.array().cast("array<long>")
    edges = longs(cuts)
    # how many cuts are above the id, by binary search
    steps = [1 << i for i in reversed(range(max(1, n).bit_length()))]
    above = F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), lambda p, s: F.when((p + s <= n) & (F.coalesce(F.get(edges, p + s - 1), F.lit(low)) > F.col("at")), p + s).otherwise(p))
    own = own.withColumn("above", above)
    share = F.coalesce(F.get(longs(shares), F.col("above")), F.lit(1).cast("long"))
    inside = F.least(share - 1, F.floor(F.col("turn") / F.lit(float(1 << 63)) * share))
    own = own.withColumn("range", (F.get(longs(base), F.col("above")) + F.when(F.get(edges, F.col("above")) == F.col("at"), inside).otherwise(F.lit(0).cast("long"))).cast("int")).drop("above")
    firsts = dict(own.groupBy("range").agg(F.max(F.struct("at", (-F.col("turn")).alias("turn")))).collect())  # one row a range
    filled = sorted(firsts)
    before = {r: filled[i - 1] for i, r in enumerate(filled)}
    first = lambda k: longs([firsts[r][k] if r in firsts else low for r in range(total)])
    echo_to = F.array(*(F.lit(before.get(r, 0)) for r in range(total)))
    echo = (F.col("at") == F.get(first("at"), F.col("range"))) & (-F.col("turn") == F.get(first("turn"), F.col("range")))
    here = F.struct(F.col("range").alias("to"), F.lit(0).alias("echo"))
    target = F.when(echo, F.array(here, F.struct(F.get(echo_to, F.col("range")).alias("to"), F.lit(1).alias("echo")))).otherwise(F.array(here))
    sent = own.withColumn("_t", F.explode(target)).select(F.col("_t.to").alias("to"), F.col("_t.echo").alias("echo"), "doc_id", "at", "turn", "text")
    placed = sent.repartitionById(total, F.col("to")).sortWithinPartitions("to", "echo", F.desc("at"), "turn", "text").select("to", "echo", "doc_id", "text")
    ddl = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"

    def run(batches):
        from hashlib import sha256

        import pyarrow as pa

        from assetmill.llm.batches import slices

        schema = arrow_schema(ddl)

        def pair(row, nxt):
            doc_id, text, mine = row
            half = len(text) // 2
            edited = (text[: len(text) - half] + nxt[1][:half]).encode()
            other = digest(edited)
            return doc_id, len(text), sha256(edited).hexdigest(), to_text(mine), to_text(other), likeness(mine, other), likeness(mine, nxt[2])

        held, at_range = None, None
        for columns in slices(batches):
            out = []
            for to, echo, doc_id, buf in zip(*columns):
                if echo and (held is None or at_range != to):
                    continue
                now = (doc_id, buf.decode("utf-8", "replace"), digest(buf))
                if held is not None and at_range == to:
                    out.append(pair(held, now))
                held, at_range = (None, None) if echo else (now, to)
            if out:
                yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)

    return placed.mapInArrow(tidy(run), ddl)
