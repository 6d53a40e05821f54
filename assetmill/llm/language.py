"""Language identification by fusing evidence the Bayesian way.

The likelihood of a text under each language comes from hashed byte trigrams. Three more pieces of
evidence shift it: the language that the markup declares, the suffix of the address, and a prior of the
host, which is smoothed towards its domain and that towards the whole corpus. The tables behind the
last three are grouped sums of text-only posteriors over all rows, so they need no labels.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assetmill.llm.batches import map_rows, raw_text
from assetmill.plans.bounded import small_side
from assetmill.plans.scratch import Scratch

CELLS = 1 << 16
#: Labelled rows that the trigram tables are fitted on, the first by a hash of doc_id.
FIT_ROWS = 4000
#: Tasks that count the sample, and different languages that may be in it: each task sends one vector a language.
FIT_TASKS, MOST_LANGUAGES = 4, 100
#: Share of a trigram's log-likelihood that counts, as neighbouring trigrams overlap.
TEMPER = 0.33
#: Weight, in rows, of a domain's languages in its hosts' and of the corpus's in its domains'.
SMOOTH = 20.0
#: Rows without a letter, or whose best language is less likely than this, are rejected.
LEAST_POSTERIOR = 0.5

_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_WEIGHT = np.array([0x9E37, 0x85EB, 0xC2B3], dtype=np.uint32)


def trigram_cells(buf: bytes) -> np.ndarray:
    """Cells of a text's byte trigrams: letters folded to lower case, all else to spaces, runs of spaces
    left out."""
    b = np.frombuffer(b" " + b" ".join(buf.translate(_FOLD).split()) + b" ", dtype=np.uint8).astype(np.uint32)
    if len(b) < 3:
        return np.zeros(0, dtype=np.uint32)
    h = b[:-2] * _WEIGHT[0] + b[1:-1] * np.uint32(0x27D4EB2F) + b[2:] * np.uint32(0x165667B1)
    return (h * np.uint32(0x9E3779B1)) >> np.uint32(16)


def fit(docs: DataFrame, rows: int = FIT_ROWS) -> tuple[list[str], np.ndarray]:
    """Languages in order and their log-probabilities of cells, from a bounded sample of rows with a
    label in ``lang``: the first by a hash of doc_id, among equal ids by a hash of the text. The sample is
    drawn where rows are scanned and then dealt to a few tasks; the driver gets one count vector a language
    and task. More than ``MOST_LANGUAGES`` labels raise an error."""
    named = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull())
    turn = F.md5(F.col("doc_id").cast("string"))
    ids = named.select("doc_id").orderBy(turn, "doc_id").limit(rows).distinct()
    sample = named.join(F.broadcast(ids), "doc_id", "left_semi").select(turn.alias("turn"), "doc_id", F.xxhash64("text").alias("h"), "lang", raw_text().alias("text")).orderBy("turn", "doc_id", "h", "lang").limit(rows)
    sample = sample.select("lang", "text").repartition(FIT_TASKS)

    def run(batches):
        import pyarrow as pa

        from assetmill.llm.batches import slices

        sums: dict[str, np.ndarray] = {}
        for langs, texts in slices(batches):
            for lang, buf in zip(langs, texts):
                own = sums.setdefault(lang, np.zeros(CELLS, dtype=np.int64))
                own += np.bincount(trigram_cells(buf), minlength=CELLS)
                if len(sums) > MOST_LANGUAGES:
                    raise ValueError(f"more than {MOST_LANGUAGES} languages")
        yield pa.record_batch([pa.array(list(sums), pa.string()), pa.array([v.astype(np.int32).tobytes() for v in sums.values()], pa.binary())], names=["lang", "counts"])

    from assetmill.plans.ship import ship

    ship(docs.sparkSession)
    totals: dict[str, np.ndarray] = {}
    for lang, raw in sample.mapInArrow(run, "lang string, counts binary").collect():
        totals[lang] = totals.get(lang, 0) + np.frombuffer(raw, dtype=np.int32).astype(np.float64)
    langs = sorted(totals)
    if len(langs) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    if not langs:
        return [], np.zeros((CELLS, 0), dtype=np.float32)
    table = np.stack([np.log((totals[k] + 0.1) / (totals[k].sum() + 0.1 * CELLS)) for k in langs], axis=1)
    return langs, (table * TEMPER).astype(np.float32)


def _grouped(rows: DataFrame, keys: list[str], n: int) -> DataFrame:
    return rows.groupBy(*keys).agg(F.count(F.lit(1)).cast("double").alias("n"), F.array(*(F.sum(F.get("own", F.lit(k))) for k in range(n))).alias("mass"))


def identify(docs: DataFrame, scratch: Scratch, host: Column | None = None, suffix: Column | None = None, declared: Column | None = None, model: tuple[list[str], np.ndarray] | None = None) -> DataFrame:
    """One row per row of ``docs``: doc_id, lang (null if none is known), posterior, text_lang, n_letters,
    rejected.

    ``host``, ``suffix`` and ``declared`` are columns of evidence, null where there is none; without a
    host the column ``source`` stands for it, if there is one. A host's domain is what follows its first
    dot, or its name without digits. Null texts count as empty; texts without letters are rejected, as
    are rows without a likely language; equal rows get equal results; without labelled rows every row is
    rejected; an empty table gives no rows.
    """
    langs, table = model or fit(docs)
    n = len(langs)
    if host is None:
        host = F.col("source") if "source" in docs.columns else F.lit(None)
    none = F.lit(None).cast("string")
    name = host.cast("string")
    domain = F.when(name.contains("."), F.substring_index(name, ".", -2)).otherwise(F.regexp_replace(name, "[0-9]+", ""))
    read = docs.select("doc_id", name.alias("host"), domain.alias("domain"), (none if suffix is None else suffix.cast("string")).alias("suffix"), (none if declared is None else F.lower(declared.cast("string"))).alias("declared"), raw_text().alias("text"))
    sent = docs.sparkSession.sparkContext.broadcast(table)

    def make():
        scores = sent.value

        def one(doc_id, host, domain, suffix, declared, buf):
            cells = trigram_cells(buf)
            letters = sum(map(len, buf.translate(_FOLD).split()))
            loglik = scores[cells].sum(axis=0, dtype=np.float64) if n else np.zeros(0)
            own = np.exp(loglik - loglik.max()) if n else loglik
            return doc_id, host, domain, suffix, declared, letters, (loglik - loglik.max() if n else loglik).tolist(), (own / own.sum() if n and letters else np.full(n, 1 / max(n, 1))).tolist()

        return one

    name_type = "string" if read.schema["doc_id"].dataType.simpleString() == "string" else "long"
    rows = scratch.keep(map_rows(read, make, f"doc_id {name_type}, host string, domain string, suffix string, declared string, n_letters int, loglik array<double>, own array<double>"), "scored")
    if not n:
        return rows.select("doc_id", none.alias("lang"), F.lit(None).cast("double").alias("posterior"), none.alias("text_lang"), "n_letters", F.lit(True).alias("rejected"))
    flat = F.array(*[F.lit(1.0 / n)] * n)
    heard = rows.where("n_letters > 0")
    whole = heard.agg(F.count(F.lit(1)).cast("double").alias("n"), F.array(*(F.sum(F.get("own", F.lit(k))) for k in range(n))).alias("mass")).first()
    total = whole["n"] or 0.0
    base = [((m or 0.0) + SMOOTH / n) / (total + SMOOTH) for m in (whole["mass"] or [0.0] * n)]
    base_c = F.array(*map(F.lit, base))

    def lean(mass: Column, count: Column, towards: Column) -> Column:
        return F.zip_with(mass, towards, lambda m, t: (m + SMOOTH * t) / (count + SMOOTH))

    domains = scratch.keep(_grouped(heard, ["domain"], n).select(F.col("domain").alias("d"), lean(F.col("mass"), F.col("n"), base_c).alias("domain_share")), "domains")
    hosts = scratch.keep(_grouped(heard, ["host", "domain"], n).select(F.col("host").alias("h"), F.col("domain").alias("hd"), F.col("n").alias("host_n"), F.col("mass").alias("host_mass")), "hosts")
    priors = hosts.join(small_side(domains), F.col("hd").eqNullSafe(F.col("d")), "left").drop("d")
    out = rows.join(small_side(scratch.keep(priors, "priors")), F.col("host").eqNullSafe(F.col("h")) & F.col("domain").eqNullSafe(F.col("hd")), "left")
    # a row's own part is taken out of its host's sums
    counted = F.col("n_letters") > 0
    rest = F.when(counted, F.zip_with("host_mass", "own", lambda m, o: F.greatest(m - o, F.lit(0.0)))).otherwise(F.col("host_mass"))
    rest_n = F.col("host_n") - F.when(counted, 1.0).otherwise(0.0)
    prior = F.when(F.col("host").isNotNull() & F.col("host_n").isNotNull(), lean(rest, rest_n, F.coalesce("domain_share", base_c))).otherwise(base_c)
    out = out.withColumn("score", F.zip_with("loglik", prior, lambda a, p: a + F.log(p)))
    for what in ("suffix", "declared"):
        # chance of the sign under each language, from the same grouped sums
        signs = scratch.keep(_grouped(heard.where(F.col(what).isNotNull()), [what], n).select(F.col(what).alias("s"), F.col("mass").alias("sign_mass")), what)
        all_mass = signs.agg(F.array(*(F.sum(F.get("sign_mass", F.lit(k))) for k in range(n))).alias("m"), F.count(F.lit(1)).alias("kinds")).first()
        if not all_mass["kinds"]:
            continue
        chance = F.zip_with("sign_mass", F.array(*map(F.lit, all_mass["m"])), lambda m, t: (m + 0.5) / (t + 0.5 * float(all_mass["kinds"])))
        out = out.join(small_side(signs), F.col(what) == F.col("s"), "left").withColumn("score", F.when(F.col("sign_mass").isNotNull(), F.zip_with("score", chance, lambda a, c: a + F.log(c))).otherwise(F.col("score"))).drop("s", "sign_mass")
    names = F.array(*map(F.lit, langs))
    top = F.array_max("score")
    weight = F.transform("score", lambda s: F.exp(s - top))
    posterior = F.lit(1.0) / F.aggregate(weight, F.lit(0.0), lambda a, x: a + x)
    out = out.withColumn("posterior", posterior).withColumn("best", F.get(names, F.array_position("score", top) - 1)).withColumn("text_lang", F.get(names, F.array_position("own", F.array_max("own")) - 1))
    rejected = (F.col("n_letters") == 0) | (F.col("posterior") < LEAST_POSTERIOR)
    return out.select("doc_id", F.when(~rejected, F.col("best")).alias("lang"), "posterior", "text_lang", "n_letters", rejected.alias("rejected"))


def markup_language(html: Column) -> Column:
    """The language that a page's root element declares, without its region."""
    found = F.regexp_extract(html, r"(?i)<html\b[^>]*?\blang\s*=\s*[\"']?([A-Za-z]{2,3})", 1)
    return F.when(found != "", F.lower(found))


def visible_text(html: Column) -> Column:
    """A page's text: scripts, styles, comments and tags out, entities left as they are."""
    bare = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->", " ")
    return F.regexp_replace(bare, r"<[^>]*>", " ")


def address_host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/:?#]+)", 1))
