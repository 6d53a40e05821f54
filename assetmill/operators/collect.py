"""Collection: addresses, fetch outcomes, content keys, crawl manifest."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def content_key(payload: Column) -> tuple[Column, Column]:
    """SHA-256 of a payload and the locator derived from it."""
    sha = F.sha2(payload, 256)
    return sha, F.concat(F.lit("cas/"), F.substring(sha, 1, 2), F.lit("/"), sha)


def resolve_urls(pages: DataFrame) -> DataFrame:
    """scheme, host and path of each address, and why it is dropped, if it is."""
    host = F.lower(F.regexp_extract("url", r"^https?://([^/:?#]+)", 1))
    out = pages.withColumn("scheme", F.regexp_extract("url", r"^(https?)://", 1)).withColumn("host", host).withColumn("path", F.regexp_extract("url", r"^https?://[^/?#]+([^?#]*)", 1))
    reason = F.when((F.col("scheme") == "") | (F.col("host") == ""), "unresolved").when(F.col("html").isNull() | (F.length("html") == 0), "dead").when(F.col("host").rlike("spam|casino|pills"), "blocked")
    return out.withColumn("drop_reason", reason)


def fetch_outcome(resolved: DataFrame) -> DataFrame:
    """Declared type by the path's ending, type by the leading bytes, and the outcome."""
    declared = F.when(F.col("path").rlike(r"\.(png|jpe?g|gif|webp)$"), "image").otherwise("html")
    magic = F.when(F.lower(F.substring("html", 1, 9)).isin("<!doctype"), "html").when(F.substring("html", 2, 3) == "PNG", "image").otherwise("unknown")
    out = resolved.withColumn("declared_type", declared).withColumn("magic", magic)
    return out.withColumn("outcome", F.when(F.col("drop_reason").isNotNull(), F.col("drop_reason")).when(F.col("declared_type") != F.col("magic"), "mismatch").when(F.octet_length("html") < 2000, "small").otherwise("ok"))


def crawl_manifest(pages: DataFrame) -> DataFrame:
    sha, locator = content_key(F.col("html"))
    return fetch_outcome(resolve_urls(pages)).select("page_id", "scheme", "host", "path", "declared_type", "magic", F.octet_length("html").cast("long").alias("body_bytes"), sha.alias("sha256"), locator.alias("locator"), "outcome")
