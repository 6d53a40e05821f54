"""Queries ``opN_<name>`` and ``pipeline`` with their SQL twins."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from assetmill.llm import bytepair, digest, language, mixing, secrets, sharding, simhash, suffixes, toxicity, vectors
from assetmill.plans.scratch import Scratch
from assetmill.sources.tables import table


def op1_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "mix") as scratch:
        mixed = mixing.mix(table(spark, sf_dir, "documents"), scratch)
    return mixed.selectExpr("doc_id", "size", "source_size", "target", "taken", "round(position, 6) AS position", "round(again, 6) AS again")


def op6_shard(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "shard") as scratch:
        return sharding.shard(table(spark, sf_dir, "documents"), scratch)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op3_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "repeats") as scratch:
        return suffixes.remove_repeats(table(spark, sf_dir, "documents"), scratch)


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents: the text, markup inside it if there is any, and the source in the place of a host."""
    docs = table(spark, sf_dir, "documents")
    with Scratch(spark, "language") as scratch:
        return language.identify(docs, scratch, declared=language.markup_language(F.col("text")))


def op4_language_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages: visible text, declared language, address suffix and host; fitted on labelled documents."""
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), "url", "html", language.visible_text(F.col("html")).alias("text"))
    model = language.fit(table(spark, sf_dir, "documents"))
    host = language.address_host(F.col("url"))
    with Scratch(spark, "language") as scratch:
        out = language.identify(pages, scratch, host=host, suffix=F.substring_index(host, ".", -1), declared=language.markup_language(F.col("html")), model=model)
    return out.withColumnRenamed("doc_id", "page_id")


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base", 256).alias("base_sha256"), "spans")


def tokenizer_path() -> str:
    """The byte-level vocabulary among the public tokenizers of this machine."""
    import public_tokenizers

    return os.environ.get("ASSETMILL_TOKENIZER") or str(public_tokenizers.path("byte_bpe_50k.json"))


def op7_bytepair(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bytepair.encode(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "simhash") as scratch:
        return simhash.near_duplicates(table(spark, sf_dir, "documents"), scratch).drop("copies")


def op9_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "vectors") as scratch:
        return vectors.near_vectors(table(spark, sf_dir, "embeddings"), scratch)


def op10_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest.edited_likeness(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_mix": op1_mix, "op2_toxicity": op2_toxicity, "op3_repeats": op3_repeats, "op4_language": op4_language, "op4_language_pages": op4_language_pages, "op5_secrets": op5_secrets, "op6_shard": op6_shard,
        "op7_bytepair": op7_bytepair, "op8_simhash": op8_simhash, "op9_vectors": op9_vectors, "op10_digest": op10_digest,
    }


MIX_SQL = r"""
WITH sized AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size, md5('mix:' || coalesce(doc_id::VARCHAR, '')) AS turn FROM documents),
sums AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
ranked AS (SELECT *, ((row_number() OVER (ORDER BY source NULLS LAST)) - 1) % 3 AS class FROM sums),
weighed AS (SELECT *, CASE class WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight, 2 * source_size AS room FROM ranked),
rated AS (SELECT *, (1.5::DOUBLE * (sum(source_size) OVER ())::DOUBLE - coalesce(sum(room) OVER (ORDER BY room::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE)
  / (sum(weight) OVER (ORDER BY room::DOUBLE / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::DOUBLE AS rate FROM weighed),
targets AS (SELECT source, source_size, class, CASE WHEN room::DOUBLE / weight <= rate THEN room::DOUBLE ELSE weight * (max(CASE WHEN room::DOUBLE / weight > rate THEN rate END) OVER ()) END AS target FROM rated),
placed AS (SELECT *, coalesce(sum(size) OVER (PARTITION BY source ORDER BY turn, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM sized),
due AS (SELECT p.doc_id, p.size, p.start, t.source_size, t.class, t.target, floor(least(greatest(t.target - p.start, 0), p.size::DOUBLE))::BIGINT AS take0, floor(least(greatest(t.target - (p.start + t.source_size), 0), p.size::DOUBLE))::BIGINT AS take1
  FROM placed p JOIN targets t ON p.source IS NOT DISTINCT FROM t.source),
shares AS (SELECT *, (start + take0 / 2.0::DOUBLE) / target AS q0, (start + source_size + take1 / 2.0::DOUBLE) / target AS q1 FROM due)
SELECT doc_id, size, source_size, target, take0 + take1 AS taken,
  round(CASE WHEN take0 > 0 THEN {q0} END, 6) AS position, round(CASE WHEN take1 > 0 THEN {q1} END, 6) AS again FROM shares"""


def _mix_sql() -> str:
    def at(q: str) -> str:
        out = []
        for k, s in enumerate(mixing.SCHEDULES):
            times, scaled, done = s.knots()
            n = len(times) - 1
            parts = [f"WHEN {q} < {done[i + 1]!r}::DOUBLE THEN {times[i]!r} + 2 * ({q} - {done[i]!r}) / ({scaled[i]!r} + sqrt(greatest({scaled[i] ** 2!r}::DOUBLE + 2 * {(scaled[i + 1] - scaled[i]) * n!r}::DOUBLE * ({q} - {done[i]!r}::DOUBLE), 0)))" for i in range(n)]
            out.append(f"WHEN {k} THEN CASE WHEN {q} <= 0 THEN 0.0 {' '.join(parts)} ELSE 1.0 END")
        return f"CASE class {' '.join(out)} END"

    return MIX_SQL.replace("{q0}", at("q0")).replace("{q1}", at("q1"))


def oracle_sql() -> dict[str, str]:
    return {"op1_mix": _mix_sql()}
