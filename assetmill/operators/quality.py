"""Scores, floors, tiers and slices."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assetmill.operators.ranks import place_in_group
from assetmill.plans.bounded import small_side

#: Leading digits of a score in millionths that make a cell of ranks: 10^5 cells a stream.
SCORE_DIGITS = 6


def gram(df: DataFrame, features: list[str], target: str) -> DataFrame:
    """Sums of products of features (a constant first) and target: one pass, one row per pair."""
    cols = {"one": F.lit(1.0)} | {f: F.col(f).cast("double") for f in features} | {"target": F.col(target).cast("double")}
    names = list(cols)
    one = df.agg(*(F.sum(cols[a] * cols[b]).alias(f"{a}|{b}") for i, a in enumerate(names) for b in names[i:]))
    pairs = [F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.round(F.col(f"{a}|{b}"), 4).alias("s")) for i, a in enumerate(names) for b in names[i:]]
    return one.select(F.explode(F.array(*pairs)).alias("x")).select("x.*")


def fit_head(df: DataFrame, features: list[str], target: str, ridge: float = 1e-6) -> dict[str, float]:
    """Weights of the linear head; the driver solves a system as small as the feature list."""
    got = {(r.a, r.b): r.s for r in gram(df, features, target).collect()}
    names = ["one", *features]
    at = lambda a, b: got[a, b] if (a, b) in got else got[b, a]
    x = np.array([[at(a, b) for b in names] for a in names]) + ridge * np.eye(len(names))
    return dict(zip(names, np.linalg.solve(x, np.array([at(a, "target") for a in names])).tolist()))


def aesthetic(head: dict[str, float]) -> Column:
    return sum((F.lit(w) * F.col(f) for f, w in head.items() if f != "one"), F.lit(head["one"]))


def calibration(df: DataFrame, score: str, label: str, bins: int = 10) -> DataFrame:
    """Mean score and label in bins of equal width over 0-10."""
    return df.groupBy(F.least(F.lit(bins - 1), F.floor(F.col(score)).cast("int")).alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(score), 6).alias("mean_score"), F.round(F.avg(F.col(label).cast("double")), 6).alias("mean_label"))


def pool_adjacent(values: list[float], weights: list[float]) -> list[float]:
    """Weighted means of neighbouring bins, merged until they do not fall."""
    blocks: list[list[float]] = []
    for v, w in zip(values, weights):
        blocks.append([v, w, 1])
        while len(blocks) > 1 and blocks[-2][0] > blocks[-1][0]:
            v2, w2, n2 = blocks.pop()
            v1, w1, n1 = blocks.pop()
            blocks.append([(v1 * w1 + v2 * w2) / (w1 + w2), w1 + w2, n1 + n2])
    return [b[0] for b in blocks for _ in range(int(b[2]))]


def floor(df: DataFrame, least: float = 5.0) -> DataFrame:
    """Real rows from ``least`` up; rows without a score stay."""
    return df.where(F.col("aesthetic_score").isNull() | (F.col("aesthetic_score") >= least))


def synthetic_score(df: DataFrame) -> Column:
    """For rows that are not real: length, variety and provenance."""
    prior = F.when(F.col("media_source") == "generated", 0.5).when(F.col("media_source") == "illustration", 0.7).otherwise(0.6)
    return F.round(10 * (0.3 * F.least(F.lit(1.0), F.log1p(F.char_length("text").cast("double")) / 10) + 0.4 * F.col("variety") + 0.3 * prior), 6)


#: Cut points between the five tiers.
CUTS = (5.0, 7.0, 8.5, 9.2)


def tier_fixed(score: Column, cuts: tuple[float, ...] = CUTS) -> Column:
    return sum(((score >= c).cast("int") for c in cuts), F.lit(1))


def tier_quantile(df: DataFrame, score: str, stream: str, key: str, tiers: int = 5) -> DataFrame:
    """Tiers by rank inside each stream, exact; the first tiers take what does not divide. Ranks come in two
    levels, by cells of the rounded score, so a stream with most rows is many groups. Scores are 0 to 10, keys
    whole numbers."""
    text = F.lpad(F.round(F.col(score) * 1_000_000).cast("long").cast("string"), 8, "0")
    placed = place_in_group(df.withColumn("_order", text), [stream], "_order", [score, key], SCORE_DIGITS, rank="_rank")
    sizes = df.groupBy(F.col(stream).alias("_stream")).agg(F.count(F.lit(1)).alias("_n"))
    placed = placed.join(small_side(sizes), F.col(stream).eqNullSafe(F.col("_stream")))
    more, each = F.col("_n") % tiers, F.floor(F.col("_n") / tiers)
    tier = F.when(F.col("_rank") < more * (each + 1), F.floor(F.col("_rank") / (each + 1))).otherwise(more + F.floor((F.col("_rank") - more * (each + 1)) / F.greatest(each, F.lit(1))))
    return placed.withColumn("tier", (tier + 1).cast("int")).drop("_order", "_rank", "_stream", "_n")


def tier_sketch(df: DataFrame, score: str, stream: str, tiers: int = 5, accuracy: int = 10_000) -> DataFrame:
    """The same by cut points from a quantile sketch: one pass and a small join."""
    cuts = df.groupBy(stream).agg(F.percentile_approx(score, [i / tiers for i in range(1, tiers)], accuracy).alias("cuts"))
    return df.join(cuts, stream).withColumn("tier", F.aggregate("cuts", F.lit(1), lambda n, c: n + (F.col(score) > c).cast("int"))).drop("cuts")


def resolution_tier(w: Column, h: Column) -> Column:
    area = w.cast("long") * h
    return F.when(area >= 1024 * 1024, 3).when(area >= 512 * 512, 2).when(area >= 256 * 256, 1).otherwise(0)


def slice_of(tier: Column, resolution: Column, alignment: Column) -> Column:
    """S1 (best) to S4, and below the floor none."""
    return F.when(tier <= 1, "below_floor").when((tier >= 4) & (resolution >= 2) & (alignment > 0.65), "S1").when((tier >= 4) & (resolution >= 1), "S2").when(tier >= 3, "S3").otherwise("S4")


def synthetic_score_with_captions(df: DataFrame) -> Column:
    """The synthetic score with a fifth of it from how many of a row's captions differ."""
    return F.round(0.8 * synthetic_score(df) + 2 * F.size(F.array_distinct("captions")) / F.greatest(F.size("captions"), F.lit(1)), 6)


def merge_streams(real: DataFrame, synthetic: DataFrame) -> DataFrame:
    """Survivors of both streams, with which they come from."""
    return real.withColumn("stream", F.lit("real")).unionByName(synthetic.withColumn("stream", F.lit("synthetic")))


#: Share of odd symbols, and of a page outside its body, from which a row is dropped.
MOST_ODD, MOST_CHROME = 0.1, 0.3


def odd_share(text: Column) -> Column:
    """Characters that are neither letters, digits, blanks nor common punctuation, the stand-in for artifacts."""
    return F.char_length(F.regexp_replace(text, r"""[\p{L}\p{N} \t\n\r.,;:!?'"()-]""", "")) / F.greatest(F.char_length(text), F.lit(1))


def chrome_share(html: Column) -> Column:
    """Share of a page's bytes in navigation, advertisement and footer."""
    parts = [F.regexp_extract(html, p, 0) for p in (r"(?s)<nav>.*?</nav>", r'(?s)<div class="ad">.*?</div>', r"(?s)<footer>.*?</footer>")]
    return sum((F.octet_length(x) for x in parts), F.lit(0)) / F.greatest(F.octet_length(html), F.lit(1))


def hard_filters(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """doc_id, watermark (a line of ``marks``, source and line, stands in it), artifacts, dropped. Marks meet lines,
    not documents, so a mark that a third of all documents share is one row on its side."""
    lines = docs.select("doc_id", "source", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where("line <> ''")
    hit = lines.join(marks.select(F.col("source").alias("_s"), F.col("line").alias("_l")), F.col("source").eqNullSafe(F.col("_s")) & (F.col("line") == F.col("_l")), "left_semi").select(F.col("doc_id").alias("_d")).distinct()
    out = docs.join(hit.withColumn("_hit", F.lit(True)), F.col("doc_id") == F.col("_d"), "left")
    flagged = out.select("doc_id", F.coalesce("_hit", F.lit(False)).alias("watermark"), (F.coalesce(odd_share(F.col("text")), F.lit(0.0)) > MOST_ODD).alias("artifacts"))
    return flagged.withColumn("dropped", F.col("watermark") | F.col("artifacts"))
