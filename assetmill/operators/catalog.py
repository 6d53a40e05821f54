"""The metadata table: schema, snapshots, runs, invariants, differences, funnels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from assetmill.operators.collect import content_key

CORE = T.StructType(
    [T.StructField(n, t) for n, t in (("id", T.StringType()), ("media_path", T.StringType()), ("width", T.IntegerType()), ("height", T.IntegerType()), ("captions", T.ArrayType(T.StringType())), ("caption_sources", T.ArrayType(T.StringType())), ("caption_lengths", T.ArrayType(T.IntegerType())), ("media_source", T.StringType()), ("aesthetic_score", T.DoubleType()), ("quality_tier", T.IntegerType()), ("episodic_bucket", T.IntegerType()), ("sha256", T.StringType()))]
)
#: Cell size of the stand-in geometry and the column at which its lines wrap.
CELL_W, CELL_H, WRAP = 8, 16, 96


def geometry(text: Column) -> tuple[Column, Column]:
    """Width and height of a text drawn in fixed cells."""
    lines = F.split(text, "\n")
    longest = F.array_max(F.transform(lines, lambda s: F.char_length(s)))
    rows = F.aggregate(lines, F.lit(0), lambda n, s: n + F.greatest(F.lit(1), F.ceil(F.char_length(s) / WRAP).cast("int")))
    return (CELL_W * F.least(F.lit(WRAP), longest)).cast("int"), (CELL_H * rows).cast("int")


def media_source(source: Column) -> Column:
    n = F.regexp_extract(source, "([0-9]+)$", 1).cast("int")
    return F.when(n <= 11, "real").when(n <= 15, "generated").when(n <= 17, "illustration").otherwise("text_render")


def letter_ratio(text: Column) -> Column:
    return F.char_length(F.regexp_replace(text, r"[^\p{L}]", "")) / F.greatest(F.char_length(text), F.lit(1))


def distinct_ratio(text: Column) -> Column:
    words = F.split(text, " ")
    return F.size(F.array_distinct(words)) / F.size(words)


def assets(docs: DataFrame) -> DataFrame:
    """One row per document with geometry, source kind, features, a score on 0-10 (null unless real)."""
    sha, path = content_key(F.col("text"))
    w, h = geometry(F.col("text"))
    out = docs.select("doc_id", F.concat(F.lit("d"), F.col("doc_id").cast("string")).alias("id"), "text", path.alias("media_path"), sha.alias("sha256"), w.alias("width"), h.alias("height"), media_source(F.col("source")).alias("media_source"), "source", "lang", letter_ratio(F.col("text")).alias("letters"), distinct_ratio(F.col("text")).alias("variety"))
    score = F.round(10 * (0.6 * F.col("letters") + 0.4 * F.col("variety")), 6)
    return out.withColumn("raw_score", score).withColumn("aesthetic_score", F.when(F.col("media_source") == "real", score))


def attach(table: DataFrame, more: DataFrame, on: str = "id") -> DataFrame:
    """Annotation columns keyed by id, added without reading the payload again."""
    return table.join(more, on, "left")


def core_table(full: DataFrame) -> DataFrame:
    return full.select(*(F.col(f.name).cast(f.dataType) for f in CORE))


def publish(df: DataFrame, root: str, version: int) -> str:
    """Write a snapshot once; a version that exists is never overwritten."""
    path = f"{root}/snapshot={version}"
    df.write.mode("errorifexists").partitionBy("quality_tier").parquet(path)
    return path


def open_run(spark: SparkSession, manifest: dict) -> DataFrame:
    """Rows and columns that a run's manifest names: path, where (SQL predicates), columns."""
    df = spark.read.parquet(manifest["path"])
    for p in manifest.get("where", []):
        df = df.where(p)
    return df.select(*manifest["columns"])


def valid(df: DataFrame) -> Column:
    lengths = (F.size("captions") == F.size("caption_sources")) & (F.size("captions") == F.size("caption_lengths"))
    return F.coalesce((F.col("width") > 0) & (F.col("height") > 0) & lengths, F.lit(False))


def enforce(df: DataFrame) -> DataFrame:
    return df.where(valid(df))


def violations(df: DataFrame) -> DataFrame:
    """Rows that break an invariant, with which."""
    geometry_bad = ~F.coalesce((F.col("width") > 0) & (F.col("height") > 0), F.lit(False))
    arrays_bad = ~F.coalesce((F.size("captions") == F.size("caption_sources")) & (F.size("captions") == F.size("caption_lengths")), F.lit(False))
    return df.withColumn("violation", F.concat_ws("+", F.when(geometry_bad, "geometry"), F.when(arrays_bad, "arrays"))).where("violation <> ''")


def check_evolution(old: T.StructType, new: T.StructType) -> list[tuple[str, str]]:
    """Field and verdict for every field of either schema; only added fields may differ."""
    a, b = ({f.name: f.dataType.simpleString() for f in s} for s in (old, new))
    return sorted((k, "added" if k not in a else "missing" if k not in b else "ok" if a[k] == b[k] else "retyped") for k in a | b)


def diff(a: DataFrame, b: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """Rows changed per column between two snapshots, and rows added and removed."""
    left, right = a.select(F.col(key), *(F.col(c).alias(f"{c}_a") for c in columns), F.lit(1).alias("in_a")), b.select(F.col(key), *(F.col(c).alias(f"{c}_b") for c in columns), F.lit(1).alias("in_b"))
    j = left.join(right, key, "full")
    both = F.col("in_a").isNotNull() & F.col("in_b").isNotNull()
    counts = j.agg(*(F.sum(F.when(both & ~F.col(f"{c}_a").eqNullSafe(F.col(f"{c}_b")), 1).otherwise(0)).alias(c) for c in columns), F.sum(F.when(F.col("in_a").isNull(), 1).otherwise(0)).alias("rows_added"), F.sum(F.when(F.col("in_b").isNull(), 1).otherwise(0)).alias("rows_removed"))
    names = [*columns, "rows_added", "rows_removed"]
    return counts.select(F.explode(F.array(*(F.struct(F.lit(n).alias("item"), F.col(n).cast("long").alias("changed")) for n in names))).alias("x")).select("x.*")


def funnel(df: DataFrame, stages: list[tuple[str, Column]]) -> DataFrame:
    """Rows kept after each stage and their share of all rows; one pass."""
    so_far, sums = F.lit(True), []
    for name, keep in stages:
        so_far = so_far & F.coalesce(keep, F.lit(False))
        sums.append(F.sum(so_far.cast("long")).alias(name))
    one = df.agg(F.count(F.lit(1)).alias("_all"), *sums)
    rows = [F.struct(F.lit(i).alias("stage_no"), F.lit(n).alias("stage"), F.col(n).alias("kept"), F.round(F.col(n) / F.col("_all"), 6).alias("fraction")) for i, (n, _) in enumerate(stages)]
    return one.select(F.explode(F.array(*rows)).alias("x")).select("x.*")


def pair_supply(df: DataFrame) -> DataFrame:
    return df.agg(F.count(F.lit(1)).alias("assets"), F.sum(F.size("captions")).cast("long").alias("pairs"), F.round(F.sum(F.size("captions")) / F.count(F.lit(1)), 6).alias("captions_per_asset"))
