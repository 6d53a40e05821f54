"""Mixing sources to target weights along a curriculum whose weights change over training.

Every source has a target amount of words and a schedule, a piecewise linear weight over training
time 0..1. The integral of the schedule, scaled to the target, is the source's cumulative demand.
The documents of a source stand in a hashed order and supply words one after the other, again from
the start when all are used; a word is due when the demand reaches it, so inverting the demand at a
document's middle word gives its training position. Sorting by position yields the mix.

Only DataFrame functions run here. The running sum inside a source is taken in two levels
(``operators.ranks``), so a source with a third of all rows is many small groups.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from assetmill.operators.ranks import order_digits, place_in_group
from assetmill.plans.bounded import small_side
from assetmill.plans.scratch import Scratch

#: A word is a run of anything but space and the five ASCII controls after backspace.
WORD = r"[^\x20\x09-\x0D]+"


@dataclass(frozen=True)
class Schedule:
    """Weight at evenly spaced times from 0 to 1, linear between; only its shape counts."""

    weights: tuple[float, ...] = (1.0, 1.0)

    def knots(self) -> tuple[list[float], list[float], list[float]]:
        """Times, weights scaled to integral one, and the integral up to each time."""
        n = len(self.weights) - 1
        area = sum((a + b) / 2 / n for a, b in zip(self.weights, self.weights[1:]))
        if n < 1 or min(self.weights) < 0 or area <= 0:
            raise ValueError("a schedule needs two weights or more, none negative, not all zero")
        scaled = [w / area for w in self.weights]
        done = [0.0]
        for a, b in zip(scaled, scaled[1:]):
            done.append(done[-1] + (a + b) / 2 / n)
        return [i / n for i in range(n + 1)], scaled, done

    def invert(self, share: Column) -> Column:
        """Time at which the cumulative demand reaches ``share`` of the target."""
        times, scaled, done = self.knots()
        n = len(times) - 1
        out = F.lit(1.0)
        for i in reversed(range(n)):
            a, slope = scaled[i], (scaled[i + 1] - scaled[i]) * n
            left = share - F.lit(done[i])
            # a*x + slope*x*x/2 = left, in the form that is stable for slope near zero
            x = 2 * left / (F.lit(a) + F.sqrt(F.greatest(F.lit(a * a) + 2 * F.lit(slope) * left, F.lit(0.0))))
            out = F.when(share < done[i + 1], F.lit(times[i]) + x).otherwise(out)
        return F.when(share <= 0, F.lit(0.0)).otherwise(F.least(out, F.lit(1.0)))


#: Weights by the rank of a source, repeating, and how each of the three moves over training.
WEIGHTS = (5, 2, 1)
SCHEDULES = (Schedule((1.5, 1.0, 0.5)), Schedule((1.0, 1.0)), Schedule((0.25, 0.75, 2.0)))


def count_words(text: Column) -> Column:
    return F.when(text.isNull(), F.lit(0)).otherwise(F.regexp_count(text, F.lit(WORD))).cast("long")


def source_targets(sized: DataFrame, share: float = 1.5, most: int = 2, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """One row per source: source_size, rows, class (index of its weight), target.

    Sources rank by code point, null last, and take the weights in turn. The total of ``share`` times
    all words is dealt by weight; no target exceeds ``most`` times its source, and what a full source
    leaves is dealt again to the others, until none is above: with sources in ascending order of room
    per unit of weight, a source is full exactly if its room is within the rate that is left when all
    before it are full.
    """
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sums.withColumn("class", ((F.row_number().over(by_name) - 1) % len(weights)).cast("int"))
    ranked = ranked.withColumn("weight", F.element_at(F.array(*(F.lit(int(w)) for w in weights)), F.col("class") + 1).cast("long")).withColumn("room", F.col("source_size") * most)
    order = [F.col("room") / F.col("weight"), F.col("source").asc_nulls_last()]
    before = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    onward = Window.orderBy(*order).rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everyone = Window.partitionBy()
    rate = (F.sum("source_size").over(everyone) * F.lit(float(share)) - F.coalesce(F.sum("room").over(before), F.lit(0))) / F.sum("weight").over(onward)
    ranked = ranked.withColumn("rate", rate).withColumn("full", F.col("room") / F.col("weight") <= F.col("rate"))
    common = F.max(F.when(~F.col("full"), F.col("rate"))).over(everyone)
    return ranked.withColumn("target", F.when(F.col("full"), F.col("room").cast("double")).otherwise(F.col("weight") * common)).select("source", "source_size", "n", "class", "target")


def mix(docs: DataFrame, scratch: Scratch, share: float = 1.5, most: int = 2, weights: tuple[int, ...] = WEIGHTS, schedules: tuple[Schedule, ...] = SCHEDULES, seed: str = "mix", carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, taken, position, again.

    ``taken`` counts the words that the mix takes of it, repeats included, at most ``most`` times its
    size (``most`` is 1 or 2). ``position`` and ``again`` are the training times of its first and
    second pass, null where it has none. Rows are range-sorted by position.

    Null text counts no words and is never due; null sources are one source; equal rows and equal ids
    keep separate turns; an empty table gives no rows. Columns other than doc_id, source, text
    and those of ``carry``, which stay with their rows and settle ties, are not read.
    """
    if most not in (1, 2):
        raise ValueError("documents pass once or twice")
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    sized = scratch.keep(docs.select("doc_id", "source", count_words(F.col("text")).alias("size"), key.alias("turn"), *carry), "sized")
    targets = scratch.keep(source_targets(sized, share, most, weights), "targets")
    rows = targets.agg(F.max("n")).first()[0] or 0
    placed = place_in_group(sized, ["source"], "turn", ["doc_id", "size", *carry], order_digits(rows), value=F.col("size"), rank="_rank", before="start")
    side = small_side(targets).withColumnRenamed("source", "_source")
    joined = placed.join(side, F.col("source").eqNullSafe(F.col("_source"))).drop("_source", "n", "_rank")
    passes = []
    for i in range(most):
        due = F.col("target") - (F.col("start") + i * F.col("source_size"))
        passes.append(F.floor(F.least(F.greatest(due, F.lit(0.0)), F.col("size").cast("double"))).cast("long"))
    out = joined.withColumns({f"_take{i}": p for i, p in enumerate(passes)})

    def when_due(i: int) -> Column:
        middle = (F.col("start") + i * F.col("source_size") + F.col(f"_take{i}") / 2) / F.col("target")
        at = F.lit(None).cast("double")
        for k in range(len(weights)):
            at = F.when(F.col("class") == k, schedules[k % len(schedules)].invert(middle)).otherwise(at)
        return F.when(F.col(f"_take{i}") > 0, at)

    second = when_due(1) if most == 2 else F.lit(None).cast("double")
    taken = sum((F.col(f"_take{i}") for i in range(1, most)), F.col("_take0"))
    return out.select("doc_id", "source", "size", "source_size", "target", taken.alias("taken"), when_due(0).alias("position"), second.alias("again"), "turn", *carry).orderBy(F.col("position").asc_nulls_last(), "turn").drop("turn")


def whole_passes(mixed: DataFrame, carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the columns of ``carry`` and training position of each pass that takes a document whole, or cuts its last one:
    the rows a trainer reads, one per pass."""
    both = F.filter(F.array("position", "again"), lambda p: p.isNotNull())
    return mixed.select("doc_id", *carry, F.explode(both).alias("position"))
