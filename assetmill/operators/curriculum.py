"""Curriculum: scores, buckets, mixtures, sampling, tasks, aspect buckets and batches."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from assetmill.operators.captions import uniform
from assetmill.operators.ranks import place_in_group


def score(tier: Column, resolution: Column, wq: float = 1.0, wr: float = 0.5) -> Column:
    return wq * tier + wr * resolution


#: Rows of one score whose whole-number keys share all but the last digits stand in one cell of ranks.
KEY_DIGITS, CELL_DIGITS = 19, 4


def buckets(df: DataFrame, by: str, key: str, k: int = 8) -> DataFrame:
    """Equal-count buckets by global rank, by ``by`` (not negative, below 10^5, three decimals count) and then by
    ``key`` (whole numbers, not negative). Ranks come in two levels, by cells of score and leading digits of the
    key, so neither a window over all rows nor one over a frequent score is needed."""
    text = F.concat(F.lpad(F.round(F.col(by) * 1000).cast("long").cast("string"), 8, "0"), F.lpad(F.col(key).cast("string"), KEY_DIGITS, "0"))
    everyone = df.agg(F.count(F.lit(1)).alias("_all"))
    placed = place_in_group(df.withColumn("_order", text), [], "_order", [], 8 + KEY_DIGITS - CELL_DIGITS, rank="_rank")
    return placed.join(F.broadcast(everyone)).withColumn("episodic_bucket", (F.floor(F.col("_rank") * k / F.col("_all")) + 1).cast("int")).drop("_order", "_rank", "_all")


def bucket_predicates(cuts: list[float], by: str) -> list[str]:
    """SQL predicates of the buckets between cut points, for pushed-down reads."""
    edges = [None, *cuts, None]
    return [" AND ".join(x for x in (f"{by} >= {a}" if a is not None else "", f"{by} < {b}" if b is not None else "") if x) or "true" for a, b in zip(edges, edges[1:])]


def mixture(progress: float, k: int = 8, floor: float = 0.02) -> list[float]:
    """Bucket weights at training progress 0..1: mass moves from early to late buckets, none below the floor."""
    raw = [(1 - progress) * (k - i) + progress * (i + 1) for i in range(k)]
    rest = 1 - k * floor
    return [floor + rest * r / sum(raw) for r in raw]


def sample(df: DataFrame, weight: Column, n: int, seed: str) -> DataFrame:
    """``n`` rows without replacement, chance by weight: the least of -ln(u)/w."""
    return df.withColumn("draw", -F.log(F.greatest(uniform(F.lit(seed), F.col("id")), F.lit(1e-15))) / weight).orderBy("draw", "id").limit(n)


def tier_weights(least: int = 2, tiers: int = 5) -> dict[int, float]:
    """Sampling weight of each quality tier: none below the floor, then rising, every tier above it in use."""
    return {t: float(max(0, t - least + 1)) for t in range(1, tiers + 1)}


def by_weight(column: Column, weights: dict[int, float]) -> Column:
    return F.element_at(F.create_map(*[F.lit(x) for kv in weights.items() for x in kv]), column)


def assign_task(u: Column, weights: dict[str, float]) -> Column:
    total, at, out = sum(weights.values()), 0.0, F.lit(list(weights)[-1])
    edges = []
    for k, w in weights.items():
        at += w / total
        edges.append((k, at))
    for k, e in reversed(edges[:-1]):
        out = F.when(u < e, k).otherwise(out)
    return out


#: Weights of the training tasks in each phase, and the four axes that a phase is controlled by.
TASKS = {"early": {"text_to_image": 0.7, "colourise": 0.1, "inpaint": 0.1, "zoom_out": 0.05, "zoom_in": 0.05}, "late": {"text_to_image": 0.9, "inpaint": 0.06, "zoom_out": 0.02, "zoom_in": 0.02}}
POLICY = (("early", 256, 2, "short", "all tasks"), ("middle", 512, 3, "medium", "all tasks"), ("late", 1024, 4, "detailed", "text first"))


def policy(spark) -> DataFrame:
    """Geometry, least quality tier, caption granularity and supervision of each phase."""
    return spark.createDataFrame(list(POLICY), "phase string, geometry int, least_tier int, granularity string, supervision string")


def complex_filter(df: DataFrame, spec: dict) -> DataFrame:
    """What no reader can apply: ``match`` and ``without`` (column to pattern or substring) drop rows,
    ``drop_captions`` (a pattern on a caption's source) drops captions with their sources and lengths, aligned."""
    for col, pattern in spec.get("match", {}).items():
        df = df.where(F.col(col).rlike(pattern))
    for col, part in spec.get("without", {}).items():
        df = df.where(~F.col(col).contains(part))
    if "drop_captions" in spec:
        zipped = F.arrays_zip("captions", "caption_sources", "caption_lengths")
        left = F.filter(zipped, lambda c: ~c["caption_sources"].rlike(spec["drop_captions"]))
        df = df.withColumn("_left", left).withColumns({n: F.col(f"_left.{n}") for n in ("captions", "caption_sources", "caption_lengths")}).drop("_left")
    return df


def scalar_filter(spec: dict) -> Column:
    """min, max, equal, include and exclude per column, as one predicate that reaches the reader."""
    out = F.lit(True)
    for col, rule in spec.items():
        for kind, v in rule.items():
            c = F.col(col)
            out = out & {"min": lambda: c >= v, "max": lambda: c <= v, "equal": lambda: c == v, "include": lambda: c.isin(v), "exclude": lambda: ~c.isin(v)}[kind]()
    return out


# --- aspect buckets ------------------------------------------------------------------------------


def crops(base: int, step: int = 64, most_aspect: float = 4.0, least_fill: float = 0.5) -> list[tuple[int, int]]:
    """Crop sizes of a resolution: sides in steps, area within the token budget and not too small."""
    budget = base * base
    sides = range(step, budget // step + 1, step)
    return [(w, h) for w in sides for h in sides if least_fill * budget <= w * h <= budget and max(w, h) / min(w, h) <= most_aspect]


def retained(w: Column, h: Column, cw: Column, ch: Column) -> Column:
    """Share of an image that a centre crop of the given aspect keeps."""
    r, a = w / h, cw / ch
    return F.least(a / r, r / a)


def assign_crop(df: DataFrame, sizes: list[tuple[int, int]]) -> DataFrame:
    """The crop that keeps the most area; of equals the larger, then the narrower. Of an aspect only its best size
    can win, and between two neighbouring aspects the better is told by the product of both, so a row is placed
    by comparisons of whole numbers inside generated code."""
    best: dict[tuple[int, int], tuple[int, int]] = {}
    for w, h in sizes:
        g = math.gcd(w, h)
        best[w // g, h // g] = max(best.get((w // g, h // g), (0, 0)), (w, h), key=lambda c: (c[0] * c[1], -c[0]))
    ranked = [best[k] for k in sorted(best, key=lambda a: a[0] / a[1])]
    w, h = F.col("width").cast("double"), F.col("height").cast("double")
    place = F.lit(0)
    for (w0, h0), (w1, h1) in zip(ranked, ranked[1:]):
        side, edge = w * w * float(h0 * h1), h * h * float(w0 * w1)
        upper = (w1 * h1, -w1) > (w0 * h0, -w0)
        place = place + (side >= edge if upper else side > edge).cast("int")
    at = lambda i: F.get(F.array(*(F.lit(c[i]) for c in ranked)), F.col("_at"))
    out = df.withColumn("_at", place).withColumns({"crop_w": at(0), "crop_h": at(1)})
    return out.withColumn("kept", F.round(retained(F.col("width"), F.col("height"), F.col("crop_w"), F.col("crop_h")), 9)).drop("_at")


def crop_box(w: Column, h: Column, cw: Column, ch: Column) -> tuple[Column, Column, Column, Column]:
    """Centre box of the crop's aspect: x, y, width, height."""
    scale = F.least(w / cw, h / ch)
    bw, bh = F.floor(cw * scale), F.floor(ch * scale)
    return F.floor((w - bw) / 2), F.floor((h - bh) / 2), bw, bh


#: Leading hex digits of an order that make a cell of ranks.
ORDER_DIGITS = 3


def batches(df: DataFrame, bucket: list[str], key: str, size: int, seed: str, scratch, drop_last: bool = True) -> DataFrame:
    """Shuffle inside buckets, pack into batches, shuffle the batches: batch, slot, batch_rank. A bucket's last
    batch, if not full, goes, or with ``drop_last`` off stays short. Both orders are by hash and ranked in two
    levels, so no window holds a bucket or all batches."""
    turn = F.md5(F.concat_ws(":", F.lit(seed), F.col(key).cast("string")))
    placed = place_in_group(df.withColumn("_turn", turn), bucket, "_turn", [key], ORDER_DIGITS, rank="_rn")
    placed = placed.withColumn("batch", F.floor(F.col("_rn") / size).cast("int")).withColumn("slot", (F.col("_rn") % size).cast("int"))
    placed = scratch.keep(placed.drop("_turn", "_rn"), "placed")
    heads = placed.groupBy(*bucket, "batch").agg(F.count(F.lit(1)).alias("_n"))
    if drop_last:
        heads = heads.where(F.col("_n") == size)
    order = F.md5(F.concat_ws(":", F.lit(f"{seed}-batch"), *(F.col(b).cast("string") for b in bucket), F.col("batch").cast("string")))
    ranked = place_in_group(heads.withColumn("_order", order), [], "_order", [], ORDER_DIGITS, rank="batch_rank").drop("_order", "_n")
    return placed.join(ranked, [*bucket, "batch"])


def to_workers(df: DataFrame, workers: int) -> DataFrame:
    return df.withColumn("worker", F.pmod("batch_rank", F.lit(workers)))


def resume(df: DataFrame, offset: int) -> DataFrame:
    """What is left after ``offset`` batches."""
    return df.where(F.col("batch_rank") >= offset)


# --- fetch health ---------------------------------------------------------------------------------


def failure_rate(events: DataFrame, grain: str) -> DataFrame:
    bad = (F.col("event_type") == "error").cast("double")
    return events.groupBy(F.date_trunc(grain, "ts").alias("bucket")).agg(F.count(F.lit(1)).alias("n"), F.sum(bad).cast("long").alias("failed"), F.round(F.avg(bad), 6).alias("rate"))


def alerts(events: DataFrame, threshold: float = 0.35, grain: str = "hour") -> DataFrame:
    return failure_rate(events, grain).where(F.col("rate") > threshold)


def substitute(events: DataFrame, by: list[str] | None = None) -> DataFrame:
    """A failed fetch takes the last success of the same ``by`` (the user if not given, else a bucket of one shape).
    Days are looked through on their own and get the last success of the days before from one row a day, so a
    frequent bucket is many windows."""
    keys = by or ["user_id"]
    ok = F.when(F.col("event_type") != "error", F.col("value"))
    day = events.withColumn("_day", F.to_date("ts")).withColumn("_ok", ok)
    inside = Window.partitionBy(*keys, "_day").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = day.where("_ok IS NOT NULL").groupBy(*keys, "_day").agg(F.max_by("_ok", F.struct("ts", "event_id")).alias("_last"))
    days = day.select(*keys, "_day").distinct().join(last, [*keys, "_day"], "left")
    carried = days.withColumn("_before", F.last("_last", ignorenulls=True).over(Window.partitionBy(*keys).orderBy("_day").rowsBetween(Window.unboundedPreceding, -1))).drop("_last")
    return day.withColumn("_in", F.last("_ok", ignorenulls=True).over(inside)).join(carried, [*keys, "_day"]).withColumn("used", F.coalesce("_ok", "_in", "_before")).drop("_day", "_ok", "_in", "_before")
