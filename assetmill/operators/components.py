"""Connected components of an edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assetmill.plans.bounded import small_side
from assetmill.plans.scratch import Scratch


def _large_star(edges: DataFrame) -> DataFrame:
    """Every neighbour above a node is tied to the least node around it."""
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), F.least("u", "m").alias("m"))
    return both.join(least, both.u == least.c).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")


def _small_star(edges: DataFrame) -> DataFrame:
    """A node and all neighbours below it are tied to the least of them. Edges have u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), "m")
    below = edges.join(least, edges.u == least.c).where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return below.union(least.select(F.col("c").alias("u"), F.col("m").alias("v"))).distinct()


def components(edges: DataFrame, scratch: Scratch, name: str = "cc", most_rounds: int = 60) -> DataFrame:
    """Map every node that has an edge to the least node it reaches: columns ``node``, ``component``.

    ``edges`` has two columns of one orderable type; loops, repeats and either direction are fine.
    Each round is written to the shared folder, so lineage stays short. Sums over a node's edges are
    pre-aggregated and the joins are plain equi-joins, which adaptive execution splits where a hub
    holds many edges.
    """
    a, b = edges.columns[:2]
    clean = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    now, seen = scratch.keep(clean, f"{name}-0"), None
    for turn in range(1, most_rounds + 1):
        later = scratch.keep(_small_star(_large_star(now).distinct()), f"{name}-{turn}")
        state = later.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        scratch.drop(f"{name}-{turn - 1}")
        now = later
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


#: Members beyond which a group's label is sent to all tasks instead of meeting its members in one.
LARGE_GROUP = 500


def spread(members: DataFrame, key: str, value: Column, name: str) -> DataFrame:
    """``members`` with ``name``, an aggregate of all rows of the same ``key`` (not null). Groups are summed with
    partial aggregation; large ones, of which there are few, go to their members by broadcast behind a size check,
    so no group's rows meet in one task."""
    groups = members.groupBy(F.col(key).alias("_g")).agg(value.alias(name), F.count(F.lit(1)).alias("_rows"))
    large = groups.where(F.col("_rows") > LARGE_GROUP).drop("_rows")
    hot, match = small_side(large), F.col(key) == F.col("_g")
    few = members.join(hot, match, "left_anti").join(groups.where(F.col("_rows") <= LARGE_GROUP).drop("_rows"), match)
    return few.union(members.join(hot, match)).drop("_g")
