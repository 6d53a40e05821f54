"""Caption candidates, alignment, routing, selection."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

HIGH, LOW = 0.65, 0.30


def granular(text: Column) -> tuple[Column, Column, Column, Column]:
    """First line, first sentence, first 60 words, first 250 words."""
    words = F.split(text, " ")
    return F.substring_index(text, "\n", 1), F.substring_index(text, ".", 1), F.array_join(F.slice(words, 1, 60), " "), F.array_join(F.slice(words, 1, 250), " ")


def token_len(caption: Column, tokenizer=None) -> Column:
    """Tokens of a caption: words, or what ``tokenizer``, a function of the column, counts."""
    return tokenizer(caption) if tokenizer else F.size(F.split(caption, " "))


def assemble(df: DataFrame) -> DataFrame:
    """captions, caption_sources and caption_lengths, aligned."""
    crawl, short, medium, detailed = granular(F.col("text"))
    return df.withColumns({"captions": F.array(crawl, short, medium, detailed), "caption_sources": F.array(*map(F.lit, ("crawl", "short", "medium", "detailed"))), "caption_lengths": F.array(*map(token_len, (crawl, short, medium, detailed)))})


def align_lexical(caption: Column, context: Column) -> Column:
    """Share of a caption's distinct words that its context has."""
    a, b = F.array_distinct(F.split(F.lower(caption), " ")), F.array_distinct(F.split(F.lower(context), " "))
    return F.when(caption.isNotNull() & (caption != ""), F.size(F.array_intersect(a, b)) / F.size(a))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def align_vector(v: Column, centre: Column) -> Column:
    return 2.5 * F.greatest(F.lit(0.0), cosine(v, centre))


def route(s: Column, high: float = HIGH, low: float = LOW) -> Column:
    """Both bounds belong to refine; without a score there is nothing to keep."""
    return F.when(s.isNull() | (s < low), "synthesize").when(s > high, "preserve").otherwise("refine")


def sweep(scored: DataFrame, score: str, label: str, steps: int = 20) -> DataFrame:
    """Precision and recall of keeping rows at or above each threshold, from a histogram."""
    bins = scored.groupBy(F.least(F.lit(steps - 1), F.floor(F.col(score) * steps).cast("int")).alias("bin")).agg(F.sum(F.col(label).cast("long")).alias("good"), F.count(F.lit(1)).alias("n"))
    up = Window.orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, 0)
    all_ = Window.partitionBy()
    out = bins.select("bin", F.sum("good").over(up).alias("tp"), F.sum("n").over(up).alias("kept"), F.sum("good").over(all_).alias("p"))
    return out.select((F.col("bin") / steps).alias("threshold"), "tp", "kept", F.round(F.col("tp") / F.col("kept"), 6).alias("precision"), F.round(F.col("tp") / F.col("p"), 6).alias("recall"), F.round(2 * F.col("tp") / (F.col("kept") + F.col("p")), 6).alias("f1"))


def pick_captioner(df: DataFrame) -> Column:
    """Texts dense in digits or symbols go to the precise model."""
    symbols = F.char_length(F.regexp_replace("text", r"[\p{L} \t\n\r.,]", "")) / F.greatest(F.char_length("text"), F.lit(1))
    return F.when(symbols > 0.05, "precise").otherwise("fast")


def request(route_: Column, locator: Column, source: Column, web_text: Column) -> Column:
    """What a captioner is given: refine sees the web text, synthesize does not."""
    return F.when(route_ == "refine", F.to_json(F.struct(locator.alias("pixels"), web_text.alias("web_text")))).when(route_ == "synthesize", F.to_json(F.struct(locator.alias("pixels"), source.alias("provenance"))))


def append(df: DataFrame, new: str, source: str) -> DataFrame:
    """One more caption; the others stay."""
    return df.withColumns({"captions": F.concat("captions", F.array(F.col(new))), "caption_sources": F.concat("caption_sources", F.array(F.lit(source))), "caption_lengths": F.concat("caption_lengths", F.array(token_len(F.col(new))))})


def uniform(*parts: Column) -> Column:
    """A number in 0..1 from a hash of the parts."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 13), 16, 10).cast("double") / F.lit(float(16**13))


def choose(df: DataFrame, mix: dict[str, float], seed: str) -> DataFrame:
    """The caption source that a hashed draw picks from a mixture."""
    u, total, at, out = uniform(F.lit(seed), F.col("id")), sum(mix.values()), 0.0, F.lit(None).cast("string")
    edges = []
    for k, w in mix.items():
        at += w / total
        edges.append((k, at))
    for k, e in reversed(edges):
        out = F.when(u < e, k).otherwise(out)
    return df.withColumn("chosen", F.coalesce(out, F.lit(edges[-1][0])))
