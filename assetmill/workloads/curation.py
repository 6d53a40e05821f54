"""Curation workloads W1-W12, W28-W30."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from assetmill.operators import captions as C
from assetmill.operators import catalog, collect, curriculum, dedup, quality, validate
from assetmill.operators.components import components
from assetmill.plans.bounded import at_most, small_side
from assetmill.plans.scratch import Scratch
from assetmill.sources.tables import table

ASSETS_SQL = r"""
WITH base AS (SELECT doc_id, text, source, lang, string_split(text, chr(10)) AS lines, string_split(text, ' ') AS words, regexp_extract(source, '([0-9]+)$', 1)::INTEGER AS sn FROM documents),
raw AS (SELECT doc_id, 'd' || doc_id::VARCHAR AS id, text, source, lang, sha256(text) AS sha256, 'cas/' || substr(sha256(text), 1, 2) || '/' || sha256(text) AS media_path,
  (8 * least(96, list_max(list_transform(lines, lambda s: length(s)))))::INTEGER AS width,
  (16 * list_sum(list_transform(lines, lambda s: greatest(1, ceil(length(s) / 96.0::DOUBLE)))))::INTEGER AS height,
  CASE WHEN sn <= 11 THEN 'real' WHEN sn <= 15 THEN 'generated' WHEN sn <= 17 THEN 'illustration' ELSE 'text_render' END AS media_source,
  length(regexp_replace(text, '[^\p{L}]', '', 'g'))::DOUBLE / greatest(length(text), 1) AS letters, len(list_distinct(words))::DOUBLE / len(words) AS variety FROM base),
scored AS (SELECT *, round(10 * (0.6::DOUBLE * letters + 0.4::DOUBLE * variety), 6) AS raw_score FROM raw),
assets AS (SELECT *, CASE WHEN media_source = 'real' THEN raw_score END AS aesthetic_score,
  1 + (raw_score >= 5.0)::INTEGER + (raw_score >= 7.0)::INTEGER + (raw_score >= 8.5)::INTEGER + (raw_score >= 9.2)::INTEGER AS quality_tier,
  CASE WHEN width::BIGINT * height >= 1048576 THEN 3 WHEN width::BIGINT * height >= 262144 THEN 2 WHEN width::BIGINT * height >= 65536 THEN 1 ELSE 0 END AS resolution FROM scored)
"""


def assets(spark: SparkSession, sf_dir: str) -> DataFrame:
    full = catalog.assets(table(spark, sf_dir, "documents"))
    return full.withColumn("quality_tier", quality.tier_fixed(F.col("raw_score"))).withColumn("resolution", quality.resolution_tier(F.col("width"), F.col("height")))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Assets, validity, exact duplicates, tiers, captions, curriculum buckets: training-facing rows."""
    full = assets(spark, sf_dir)
    full = validate.run_tiers(full, [validate.positive_geometry(F.col("width"), F.col("height")), validate.decodable(F.col("text"))])
    keep = full.groupBy("sha256").agg(F.min("doc_id").alias("doc_id"))
    full = quality.floor(full.join(keep, ["sha256", "doc_id"], "left_semi"))
    full = C.assemble(full).withColumn("rank_score", curriculum.score(F.col("quality_tier"), F.col("resolution")))
    return catalog.core_table(curriculum.buckets(full, "rank_score", "doc_id"))


def w01(spark, d):
    a = assets(spark, d).select("doc_id", "sha256", F.col("text").isNotNull().alias("fetched"), "width", "height", "aesthetic_score", "quality_tier")  # no payload is shuffled
    a = a.join(table(spark, d, "labels").select("doc_id", "toxic"), "doc_id", "left")
    first = a.groupBy("sha256").agg(F.min("doc_id").alias("doc_id")).withColumn("first", F.lit(True)).drop("sha256")
    a = a.join(first, "doc_id", "left").withColumn("first", F.coalesce("first", F.lit(False)))
    W, H = F.col("width"), F.col("height")
    return catalog.funnel(a, [("fetched", F.col("fetched")), ("valid", validate.positive_geometry(W, H) & validate.min_side(W, H)), ("heuristic", validate.aspect_ok(W, H, 8.0)), ("dedup", F.col("first")), ("safety", F.coalesce(F.col("toxic"), F.lit(0)) == 0), ("scored", F.col("aesthetic_score").isNull() | (F.col("aesthetic_score") >= 5.0)), ("curated", F.col("quality_tier") >= 3)])


W01_SQL = ASSETS_SQL + """, f AS (SELECT a.*, row_number() OVER (PARTITION BY sha256 ORDER BY a.doc_id) = 1 AS first, coalesce(toxic, 0) AS toxic FROM assets a LEFT JOIN labels l ON a.doc_id = l.doc_id),
g AS (SELECT (text IS NOT NULL) AS s0, (width > 0 AND height > 0 AND least(width, height) >= 64) AS s1, greatest(width::DOUBLE / height, height::DOUBLE / width) <= 8.0 AS s2, first AS s3, toxic = 0 AS s4, (aesthetic_score IS NULL OR aesthetic_score >= 5.0) AS s5, quality_tier >= 3 AS s6 FROM f),
c AS (SELECT count(*) AS n, """ + ", ".join(f"count(*) FILTER ({' AND '.join(f's{j}' for j in range(i + 1))}) AS k{i}" for i in range(7)) + " FROM g) " + " UNION ALL ".join(f"SELECT {i} AS stage_no, '{s}' AS stage, k{i} AS kept, round(k{i}::DOUBLE / n, 6) AS fraction FROM c" for i, s in enumerate(("fetched", "valid", "heuristic", "dedup", "safety", "scored", "curated")))


def w02(spark, d):
    return collect.crawl_manifest(table(spark, d, "pages")).select("page_id", "scheme", "host", "path", "declared_type", "magic", "body_bytes", "sha256", "outcome")


W02_SQL = r"""WITH p AS (SELECT page_id, html, regexp_extract(url, '^(https?)://', 1) AS scheme, lower(regexp_extract(url, '^https?://([^/:?#]+)', 1)) AS host, regexp_extract(url, '^https?://[^/?#]+([^?#]*)', 1) AS path FROM pages),
q AS (SELECT *, CASE WHEN scheme = '' OR host = '' THEN 'unresolved' WHEN html IS NULL OR length(html) = 0 THEN 'dead' WHEN regexp_matches(host, 'spam|casino|pills') THEN 'blocked' END AS r,
 CASE WHEN regexp_matches(path, '\.(png|jpe?g|gif|webp)$') THEN 'image' ELSE 'html' END AS declared_type, CASE WHEN lower(substr(html, 1, 9)) = '<!doctype' THEN 'html' WHEN substr(html, 2, 3) = 'PNG' THEN 'image' ELSE 'unknown' END AS magic FROM p)
SELECT page_id, scheme, host, path, declared_type, magic, strlen(html)::BIGINT AS body_bytes, sha256(html) AS sha256, CASE WHEN r IS NOT NULL THEN r WHEN declared_type <> magic THEN 'mismatch' WHEN strlen(html) < 2000 THEN 'small' ELSE 'ok' END AS outcome FROM q"""


def w03_exact(spark, d):
    return dedup.exact(assets(spark, d), "sha256", [-F.col("height"), F.col("doc_id")])


W03_EXACT_SQL = ASSETS_SQL + "SELECT sha256, arg_min(doc_id, (-height, doc_id)) AS keep_id, count(*) AS copies FROM assets GROUP BY sha256"

SETS_SQL = r"""
WITH w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
sets AS (SELECT doc_id, list_sort(list_distinct(CASE WHEN len(w) = 0 THEN []::VARCHAR[] ELSE list_transform(range(1, greatest(1, len(w) - 4) + 1), lambda i: array_to_string(w[i:i + 4], ' ')) END)) AS s FROM w),
nodes AS (SELECT s, min(doc_id) AS node, len(s) AS n FROM sets GROUP BY s),
grams AS (SELECT node, n, unnest(s) AS g FROM nodes),
shared AS (SELECT a.node AS a, b.node AS b, any_value(a.n) AS na, any_value(b.n) AS nb, count(*) AS shared FROM grams a JOIN grams b ON a.g = b.g AND a.node < b.node AND 4 * a.n <= 5 * b.n AND 4 * b.n <= 5 * a.n GROUP BY 1, 2),
pairs AS (SELECT a, b, shared::INTEGER AS shared, round(shared::DOUBLE / (na + nb - shared), 6) AS jaccard FROM shared WHERE 5 * shared >= 4 * (na + nb - shared))"""


def _sets(spark, d, s: Scratch) -> DataFrame:
    return s.keep(dedup.shingle_sets(table(spark, d, "documents")), "sets")


def w03_pairs(spark, d):
    with Scratch(spark, "pairs") as s:
        return dedup.near_sets(s.keep(dedup.set_nodes(_sets(spark, d, s)), "nodes"))


def _near(spark, d, s: Scratch) -> tuple[DataFrame, DataFrame, DataFrame]:
    """doc_id and node; near pairs of nodes; node and cluster of the nodes that have one."""
    sets = _sets(spark, d, s)
    pairs = s.keep(dedup.near_sets(s.keep(dedup.set_nodes(sets), "nodes")), "pairs")
    reach = components(pairs.select("a", "b"), s)
    return s.keep(dedup.set_names(sets), "names"), pairs, reach.withColumnRenamed("component", "cluster")


def _clusters(spark, d) -> DataFrame:
    with Scratch(spark, "clusters") as s:
        names, _, reach = _near(spark, d, s)
        return names.join(reach, "node", "left").select("doc_id", F.coalesce("cluster", "node").alias("cluster"))


def w03_star(spark, d):
    with Scratch(spark, "star") as s:
        names, pairs, _ = _near(spark, d, s)
        star = dedup.star_clusters(names.select("node").distinct(), pairs)
        return names.join(star, "node").select("doc_id", "centre")


CLUSTERS_SQL = SETS_SQL.replace("WITH w AS", "WITH RECURSIVE w AS", 1) + """, e AS (SELECT a, b FROM pairs UNION SELECT b, a FROM pairs), r(n, c) AS (SELECT node, node FROM nodes UNION SELECT e.b, r.c FROM r JOIN e ON r.n = e.a WHERE r.c < e.b),
lows AS (SELECT n, min(c) AS cluster FROM r GROUP BY n), cl AS (SELECT doc_id, node, cluster FROM sets JOIN nodes USING (s) JOIN lows ON n = node)"""
CLUSTERS_SQL = CLUSTERS_SQL.replace("r(n, c) AS (SELECT node, node", "r(rn, c) AS (SELECT node, node").replace("r.n = e.a", "r.rn = e.a").replace("SELECT n, min(c)", "SELECT rn, min(c)").replace("GROUP BY n)", "GROUP BY rn)").replace("ON n = node", "ON rn = node")


def w03_rates(spark, d):
    c = _clusters(spark, d).join(table(spark, d, "documents").select("doc_id", F.sha2("text", 256).alias("sha")), "doc_id")
    one = c.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("sha").alias("after_exact"), F.count_distinct("cluster").alias("after_near"))
    return one.select("n", "after_exact", "after_near", F.round(1 - F.col("after_exact") / F.col("n"), 6).alias("exact_rate"), F.round(1 - F.col("after_near") / F.col("after_exact"), 6).alias("near_rate"))


W03_RATES_SQL = CLUSTERS_SQL + " SELECT n, after_exact, after_near, round(1 - after_exact::DOUBLE / n, 6) AS exact_rate, round(1 - after_near::DOUBLE / after_exact, 6) AS near_rate FROM (SELECT count(*) AS n, count(DISTINCT sha256(text)) AS after_exact, count(DISTINCT cluster) AS after_near FROM cl JOIN documents USING (doc_id))"


def _members(spark, d) -> DataFrame:
    return assets(spark, d).select("doc_id", "sha256", "width", "height", "quality_tier")


def w03_survivors(spark, d):
    """One document of each near-duplicate cluster, after exact copies are gone: by area, tier and smallest id."""
    best = F.struct(F.col("width") * F.col("height"), "quality_tier", -F.col("doc_id"))
    a = _members(spark, d)
    single = a.join(a.groupBy("sha256").agg(F.max_by("doc_id", best).alias("doc_id")).select("doc_id"), "doc_id", "left_semi")
    return dedup.representative(single.join(_clusters(spark, d), "doc_id"))


MEMBERS_SQL = CLUSTERS_SQL + ", " + ASSETS_SQL.strip().removeprefix("WITH ") + ", u AS (SELECT arg_max(doc_id, (width * height, quality_tier, -doc_id)) AS doc_id FROM assets GROUP BY sha256), k AS (SELECT cluster, arg_max(doc_id, (width * height, quality_tier, -doc_id)) AS keep_id, count(*) AS members FROM assets JOIN u USING (doc_id) JOIN cl USING (doc_id) GROUP BY 1)"
W03_SURVIVORS_SQL = MEMBERS_SQL + " SELECT cluster, keep_id, members FROM k"


def w03_two_stage(spark, d):
    """What becomes of each document: removed as an exact copy, as a near copy of what that left, or kept."""
    with Scratch(spark, "two-stage") as s:
        names, _, reach = _near(spark, d, s)
        return dedup.two_stage(_members(spark, d), names, reach)


W03_TWO_SQL = MEMBERS_SQL + " SELECT doc_id, CASE WHEN doc_id IN (SELECT keep_id FROM k) THEN 'kept' WHEN doc_id IN (SELECT doc_id FROM u) THEN 'near' ELSE 'exact' END AS stage FROM assets"


def w03_diversity(spark, d):
    """Distinct clusters a row, before and after each stage."""
    with Scratch(spark, "diversity") as s:
        names, _, reach = _near(spark, d, s)
        stage = dedup.two_stage(_members(spark, d), names, reach)
        rows = s.keep(stage.join(names, "doc_id").join(reach, "node", "left").select("stage", F.coalesce("cluster", "node").alias("cluster")), "rows")
    part = lambda kept: rows.where(F.col("stage").isin(*kept)).agg(F.count(F.lit(1)).alias("n"), F.count_distinct("cluster").alias("clusters"))
    out = None
    for name, kept in DEDUP_STAGES:
        one = part(kept).select(F.lit(name).alias("after"), "n", F.round(F.col("clusters") / F.col("n"), 6).alias("diversity"))
        out = one if out is None else out.union(one)
    return out


DEDUP_STAGES = (("collection", ("exact", "near", "kept")), ("exact", ("near", "kept")), ("near", ("kept",)))
W03_DIV_SQL = MEMBERS_SQL + f", st AS ({W03_TWO_SQL.rsplit(' SELECT doc_id, CASE', 1)[1].join((' SELECT doc_id, CASE', ''))}), x AS (SELECT stage, cluster FROM st JOIN cl USING (doc_id)) " + " UNION ALL ".join(f"SELECT '{n}' AS after, count(*) AS n, round(count(DISTINCT cluster)::DOUBLE / count(*), 6) AS diversity FROM x WHERE stage IN ({', '.join(map(repr, k)) if len(k) > 1 else repr(k[0])})" for n, k in DEDUP_STAGES)


def _grid_prints(spark, d) -> DataFrame:
    """Cosine-sign hashes of the grids and of a slightly noisy copy of each, whose id is moved by a million."""
    p = pixels(spark, d).select("vec_id", "grid")
    noise = F.transform("grid", lambda x, i: x + (F.pmod(i * 7919 + F.col("vec_id"), F.lit(1009)) / 1009 - 0.5) * 1e-2)
    both = p.union(p.select((F.col("vec_id") + 1_000_000).alias("vec_id"), noise.alias("grid")))
    return dedup.phash_column(both, "grid").select("vec_id", dedup.bits_number(F.col("bits")).alias("fp"))


def w04_banded_recall(spark, d):
    """Near fingerprints found by bands beside a brute-force search of every hundredth grid against all."""
    with Scratch(spark, "brute") as s:
        prints = s.keep(_grid_prints(spark, d), "prints")
        q = prints.where("vec_id % 100 = 0")
        brute = dedup.near_bits_brute(F.broadcast(q) if at_most(q, BRUTE_QUERIES) else q, prints)
        found = dedup.near_bits(prints)
        first = prints.groupBy("fp").agg(F.min("vec_id").alias("id"))
        named = prints.join(first, "fp").select(F.col("vec_id").alias("v"), "id")
        links = found.select("a", "b").union(found.select(F.col("b").alias("a"), F.col("a").alias("b"))).union(first.select(F.col("id").alias("a"), F.col("id").alias("b")))
        asked = brute.join(named.toDF("q", "a"), "q").join(named.toDF("vec_id", "b"), "vec_id")
        hit = links.distinct().withColumn("hit", F.lit(1))
        return asked.join(hit, ["a", "b"], "left").agg(F.count(F.lit(1)).alias("brute_pairs"), F.count("hit").alias("banded_pairs"))


#: Queries up to which a search by brute force sends them to every executor.
BRUTE_QUERIES = 100_000


def pixels(spark, d) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("grid"))


def w04_ahash(spark, d):
    return pixels(spark, d).select("vec_id", dedup.ahash(F.col("grid")).alias("bits"))


W04_AHASH_SQL = "WITH g AS (SELECT vec_id, embedding::DOUBLE[64] AS grid, list_sum(embedding::DOUBLE[]) / 64 AS m FROM embeddings) SELECT vec_id, array_to_string(list_transform(grid::DOUBLE[], lambda x: CASE WHEN x > m THEN '1' ELSE '0' END), '') AS bits FROM g"


def w04_phash(spark, d):
    return dedup.phash_column(pixels(spark, d), "grid").select("vec_id", "bits")


def w04_planted(spark, d):
    """Share of planted copies (brighter, exact, noisy) within 3 bits of their source."""
    p = pixels(spark, d).select("vec_id", "grid")
    noise = F.transform("grid", lambda x, i: x + (F.pmod(i * 7919 + F.col("vec_id"), F.lit(1009)) / 1009 - 0.5) * 1e-4)
    kinds = F.array(F.struct(F.lit("brighten").alias("kind"), F.transform("grid", lambda x: x + 0.1).alias("copy")), F.struct(F.lit("exact").alias("kind"), F.col("grid").alias("copy")), F.struct(F.lit("noise").alias("kind"), noise.alias("copy")))
    p = dedup.phash_column(p, "grid")
    copies = dedup.phash_column(p.select("bits", F.explode(kinds).alias("k")).select("bits", "k.kind", "k.copy"), "copy", "copy_bits")
    c = copies.select("kind", dedup.hamming(dedup.bits_number(F.col("bits")), dedup.bits_number(F.col("copy_bits"))).alias("apart"))
    return c.groupBy("kind").agg(F.round(F.avg((F.col("apart") <= 3).cast("double")), 6).alias("recall"))


def w05_tiers(spark, d):
    kept = quality.floor(assets(spark, d))
    return kept.groupBy(F.when(F.col("media_source") == "real", "real").otherwise("synthetic").alias("stream"), "quality_tier").agg(F.count(F.lit(1)).alias("n"))


W05_TIERS_SQL = ASSETS_SQL + "SELECT CASE WHEN media_source = 'real' THEN 'real' ELSE 'synthetic' END AS stream, quality_tier, count(*) AS n FROM assets WHERE aesthetic_score IS NULL OR aesthetic_score >= 5.0 GROUP BY 1, 2"


def _labelled(spark, d):
    return assets(spark, d).join(table(spark, d, "labels"), "doc_id")


def w05_gram(spark, d):
    return quality.gram(_labelled(spark, d), ["letters", "variety"], "quality")


_G = {"one": "1.0::DOUBLE", "letters": "letters", "variety": "variety", "target": "quality::DOUBLE"}
W05_GRAM_SQL = ASSETS_SQL + ", j AS (SELECT a.*, l.quality FROM assets a JOIN labels l USING (doc_id)) " + " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b, round(sum({_G[a]} * {_G[b]}), 4) AS s FROM j" for i, a in enumerate(_G) for b in list(_G)[i:])


def w05_head(spark, d):
    """Mean score of the fitted head by label: the head tells good rows from poor ones."""
    rows = _labelled(spark, d)
    head = quality.fit_head(rows, ["letters", "variety"], "quality")
    return rows.groupBy("quality").agg(F.round(F.avg(quality.aesthetic(head)), 4).alias("mean_score"), F.count(F.lit(1)).alias("n"))


def w05_calibration(spark, d):
    return quality.calibration(_labelled(spark, d), "raw_score", "quality")


W05_CAL_SQL = ASSETS_SQL + "SELECT least(9, floor(raw_score))::INTEGER AS bin, count(*) AS n, round(avg(raw_score), 6) AS mean_score, round(avg(quality::DOUBLE), 6) AS mean_label FROM assets JOIN labels USING (doc_id) GROUP BY 1"


def w05_quantile(spark, d):
    a = assets(spark, d).select("doc_id", "raw_score", "media_source")
    return quality.tier_quantile(a, "raw_score", "media_source", "doc_id").select("doc_id", "tier")


W05_Q_SQL = ASSETS_SQL + "SELECT doc_id, ntile(5) OVER (PARTITION BY media_source ORDER BY raw_score, doc_id)::INTEGER AS tier FROM assets"


def w05_synth(spark, d):
    a = assets(spark, d).where("media_source <> 'real'")
    return a.select("doc_id", quality.synthetic_score(a).alias("score"))


W05_S_SQL = ASSETS_SQL + "SELECT doc_id, round(10 * (0.3::DOUBLE * least(1.0::DOUBLE, ln(1 + length(text)::DOUBLE) / 10) + 0.4::DOUBLE * variety + 0.3::DOUBLE * CASE media_source WHEN 'generated' THEN 0.5 WHEN 'illustration' THEN 0.7 ELSE 0.6 END), 6) AS score FROM assets WHERE media_source <> 'real'"


def w06(spark, d):
    v = aligned(spark, d).select(F.col("vec_id").alias("doc_id"), "s")
    a = assets(spark, d).join(v, "doc_id", "left")
    return a.groupBy(quality.slice_of(F.col("quality_tier"), F.col("resolution"), F.coalesce("s", F.lit(0.5))).alias("slice")).agg(F.count(F.lit(1)).alias("n"))


ALIGN_SQL = """c AS (SELECT label, i, avg(embedding[i]::DOUBLE) AS m FROM embeddings, range(1, 65) t(i) GROUP BY label, i), k AS (SELECT label, list(m ORDER BY i) AS centre FROM c GROUP BY label),
v AS (SELECT vec_id, e.label, round(2.5 * greatest(0, list_dot_product(embedding::DOUBLE[], centre) / (sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])) * sqrt(list_dot_product(centre, centre)))), 6) AS s FROM embeddings e JOIN k ON e.label = k.label)"""
W06_SQL = ASSETS_SQL + ", " + ALIGN_SQL + ", j AS (SELECT a.*, coalesce(s, 0.5) AS al FROM assets a LEFT JOIN v ON a.doc_id = v.vec_id) SELECT CASE WHEN quality_tier <= 1 THEN 'below_floor' WHEN quality_tier >= 4 AND resolution >= 2 AND al > 0.65 THEN 'S1' WHEN quality_tier >= 4 AND resolution >= 1 THEN 'S2' WHEN quality_tier >= 3 THEN 'S3' ELSE 'S4' END AS slice, count(*) AS n FROM j GROUP BY 1"


def aligned(spark, d) -> DataFrame:
    e = table(spark, d, "embeddings")
    centres = e.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("m")).groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda p: p["m"]).alias("centre"))
    return e.join(small_side(centres), "label").select("vec_id", "label", F.round(C.align_vector(F.col("embedding"), F.col("centre")), 6).alias("s"))


def w07_vectors(spark, d):
    return aligned(spark, d).select("vec_id", "s", C.route(F.col("s")).alias("route"))


W07_V_SQL = "WITH " + ALIGN_SQL + " SELECT vec_id, s, CASE WHEN s < 0.30 THEN 'synthesize' WHEN s > 0.65 THEN 'preserve' ELSE 'refine' END AS route FROM v"


def w07_pages(spark, d):
    p = table(spark, d, "pages")
    grab = lambda tag: F.regexp_extract("html", tag, 1)
    bare = lambda c: F.trim(F.regexp_replace(F.regexp_replace(c, "<[^>]*>", " "), " +", " "))
    body = bare(grab("(?s)<article>(.*?)</article>"))
    cands = F.array(*(F.struct(F.lit(n).alias("source"), bare(grab(t)).alias("caption")) for n, t in (("title", "(?s)<title>(.*?)</title>"), ("nav", "(?s)<nav>(.*?)</nav>"), ("ad", '(?s)<div class="ad">(.*?)</div>'), ("footer", "(?s)<footer>(.*?)</footer>"))))
    rows = p.select("page_id", body.alias("body"), F.explode(cands).alias("c"))
    s = F.round(C.align_lexical(F.col("c.caption"), F.col("body")), 6)
    return rows.select("page_id", "c.source", s.alias("s")).withColumn("route", C.route(F.col("s")))


_B = lambda x: f"trim(regexp_replace(regexp_replace({x}, '<[^>]*>', ' ', 'g'), ' +', ' ', 'g'), ' ')"
W07_P_SQL = "WITH b AS (SELECT page_id, " + _B("regexp_extract(html, '(?s)<article>(.*?)</article>', 1)") + " AS body, html FROM pages), c AS (" + " UNION ALL ".join(f"SELECT page_id, body, '{n}' AS source, {_B(f'''regexp_extract(html, '(?s){t}', 1)''')} AS caption FROM b" for n, t in (("title", "<title>(.*?)</title>"), ("nav", "<nav>(.*?)</nav>"), ("ad", '<div class="ad">(.*?)</div>'), ("footer", "<footer>(.*?)</footer>"))) + """),
 x AS (SELECT page_id, source, caption, list_distinct(string_split(lower(caption), ' ')) AS a, list_distinct(string_split(lower(body), ' ')) AS w FROM c), y AS (SELECT page_id, source, CASE WHEN caption IS NOT NULL AND caption <> '' THEN round(len(list_intersect(a, w))::DOUBLE / len(a), 6) END AS s FROM x)
 SELECT page_id, source, s, CASE WHEN s IS NULL OR s < 0.30 THEN 'synthesize' WHEN s > 0.65 THEN 'preserve' ELSE 'refine' END AS route FROM y"""


def w07_sweep(spark, d):
    return C.sweep(_labelled(spark, d).select((F.col("raw_score") / 10).alias("s"), "quality"), "s", "quality")


W07_SW_SQL = ASSETS_SQL + """, h AS (SELECT least(19, floor(raw_score / 10 * 20))::INTEGER AS bin, sum(quality)::BIGINT AS good, count(*) AS n FROM assets JOIN labels USING (doc_id) GROUP BY 1),
 u AS (SELECT bin, (sum(good) OVER (ORDER BY bin DESC))::BIGINT AS tp, (sum(n) OVER (ORDER BY bin DESC))::BIGINT AS kept, (sum(good) OVER ())::BIGINT AS p FROM h) SELECT bin / 20.0::DOUBLE AS threshold, tp, kept, round(tp::DOUBLE / kept, 6) AS precision, round(tp::DOUBLE / p, 6) AS recall, round(2.0::DOUBLE * tp / (kept + p), 6) AS f1 FROM u"""


def _bucketed(spark, d) -> DataFrame:
    a = assets(spark, d).withColumn("rank_score", curriculum.score(F.col("quality_tier"), F.col("resolution")))
    return curriculum.buckets(a, "rank_score", "doc_id")


BUCKET_SQL = ASSETS_SQL + ", b AS (SELECT *, (floor((row_number() OVER (ORDER BY quality_tier + 0.5::DOUBLE * resolution, doc_id) - 1) * 8 / (count(*) OVER ())::DOUBLE) + 1)::INTEGER AS episodic_bucket FROM assets)"


def w08(spark, d):
    a = C.assemble(_bucketed(spark, d))
    return a.cube("quality_tier", "episodic_bucket").agg(F.round(F.avg(F.get("caption_lengths", F.lit(3)).cast("double")), 6).alias("mean_detailed"), F.round(F.avg(F.get("caption_lengths", F.lit(1)).cast("double")), 6).alias("mean_short"), F.count(F.lit(1)).alias("n"))


W08_SQL = BUCKET_SQL + ", l AS (SELECT quality_tier, episodic_bucket, least(250, len(string_split(text, ' ')))::DOUBLE AS det, len(string_split(string_split(text, '.')[1], ' '))::DOUBLE AS sh FROM b) SELECT quality_tier, episodic_bucket, round(avg(det), 6) AS mean_detailed, round(avg(sh), 6) AS mean_short, count(*) AS n FROM l GROUP BY CUBE (quality_tier, episodic_bucket)"


def w09(spark, d):
    return _bucketed(spark, d).groupBy("quality_tier").pivot("episodic_bucket", list(range(1, 9))).count().na.fill(0).toDF("quality_tier", *(f"b{i}" for i in range(1, 9)))


W09_SQL = BUCKET_SQL + " SELECT quality_tier, " + ", ".join(f"count(*) FILTER (episodic_bucket = {i}) AS b{i}" for i in range(1, 9)) + " FROM b GROUP BY 1"


def w10_crops(spark, d):
    """Crop sizes of each base, each with the lines whose quantity is its width in steps of 64."""
    lines = table(spark, d, "lineitem").groupBy((F.col("l_quantity").cast("int") * 64).alias("side")).agg(F.count(F.lit(1)).alias("lines"))
    c = spark.createDataFrame([(b, w, h) for b in (256, 512, 1024) for w, h in curriculum.crops(b)], "base int, w int, h int")
    return c.join(lines, F.col("w") == F.col("side"), "left").select("base", "w", "h", F.coalesce("lines", F.lit(0)).alias("lines"))


W10_C_SQL = "SELECT b.base::INTEGER AS base, (w * 64)::INTEGER AS w, (h * 64)::INTEGER AS h, coalesce(n, 0) AS lines FROM (VALUES (256), (512), (1024)) b(base), range(1, 257) x(w), range(1, 257) y(h) LEFT JOIN (SELECT l_quantity::INTEGER AS q, count(*) AS n FROM lineitem GROUP BY 1) l ON l.q = w WHERE w * h * 4096 <= base * base AND w * h * 4096 >= 0.5 * base * base AND greatest(w, h) <= 4 * least(w, h)"


def w10_assign(spark, d):
    return curriculum.assign_crop(assets(spark, d), curriculum.crops(256)).select("doc_id", "crop_w", "crop_h", F.round("kept", 6).alias("kept"))


CROP_SQL = "cr AS (SELECT (w * 64)::INTEGER AS cw, (h * 64)::INTEGER AS ch FROM range(1, 257) x(w), range(1, 257) y(h) WHERE w * h * 4096 <= {a} AND w * h * 4096 >= 0.5 * {a} AND greatest(w, h) <= 4 * least(w, h))"
_R = "round(least((cw::DOUBLE / ch) / (width::DOUBLE / height), (width::DOUBLE / height) / (cw::DOUBLE / ch)), 9)"
W10_A_SQL = ASSETS_SQL + ", " + CROP_SQL.format(a=65536) + f", x AS (SELECT doc_id, cw, ch, {_R} AS kept, row_number() OVER (PARTITION BY doc_id ORDER BY {_R} DESC, cw * ch DESC, cw) AS rn FROM assets, cr) SELECT doc_id, cw AS crop_w, ch AS crop_h, round(kept, 6) AS kept FROM x WHERE rn = 1"


def w10_gain(spark, d):
    a, out = assets(spark, d), None
    for base in (256, 512, 1024):
        one = curriculum.assign_crop(a, curriculum.crops(base)).agg(F.lit(base).alias("base"), F.round(F.avg("kept"), 6).alias("multi_aspect"), F.round(F.avg(F.least(F.col("width") / F.col("height"), F.col("height") / F.col("width"))), 6).alias("square"))
        out = one if out is None else out.union(one)
    return out


W10_G_SQL = ASSETS_SQL + ", cr AS (SELECT b.base::INTEGER AS base, (w * 64)::INTEGER AS cw, (h * 64)::INTEGER AS ch FROM (VALUES (256), (512), (1024)) b(base), range(1, 257) x(w), range(1, 257) y(h) WHERE w * h * 4096 <= base * base AND w * h * 4096 >= 0.5 * base * base AND greatest(w, h) <= 4 * least(w, h))" + f", x AS (SELECT base, doc_id, max({_R}) AS kept, min(least(width::DOUBLE / height, height::DOUBLE / width)) AS sq FROM assets, cr GROUP BY base, doc_id) SELECT base, round(avg(kept), 6) AS multi_aspect, round(avg(sq), 6) AS square FROM x GROUP BY base"


def w10_scale(spark, d):
    j = table(spark, d, "lineitem").select("l_partkey", "l_quantity").join(table(spark, d, "part").select("p_partkey", "p_size"), F.col("l_partkey") == F.col("p_partkey"))
    g = j.select((F.col("l_quantity") * 16).cast("int").alias("width"), (F.col("p_size") * 16).cast("int").alias("height"))
    return curriculum.assign_crop(g, curriculum.crops(256)).groupBy("crop_w", "crop_h").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("kept"), 6).alias("mean_kept"))


W10_S_SQL = "WITH g AS (SELECT (l_quantity * 16)::INTEGER AS width, (p_size * 16)::INTEGER AS height, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2), " + CROP_SQL.format(a=65536) + f", x AS (SELECT n, cw, ch, {_R} AS kept, row_number() OVER (PARTITION BY width, height ORDER BY {_R} DESC, cw * ch DESC, cw) AS rn FROM g, cr) SELECT cw AS crop_w, ch AS crop_h, sum(n)::BIGINT AS n, round(sum(kept * n) / sum(n), 6) AS mean_kept FROM x WHERE rn = 1 GROUP BY 1, 2"


def _batches(spark, d, drop_last: bool = True):
    a = curriculum.assign_crop(assets(spark, d), curriculum.crops(256)).select("doc_id", "crop_w", "crop_h")
    with Scratch(spark, "batches") as s:
        return curriculum.to_workers(curriculum.batches(a, ["crop_w", "crop_h"], "doc_id", 8, "e0", s, drop_last), 4)


def w11_batches(spark, d):
    return _batches(spark, d).select("doc_id", "crop_w", "crop_h", "batch", "slot", F.col("batch_rank").cast("long").alias("batch_rank"), F.col("worker").cast("long").alias("worker"))


W11_SQL = W10_A_SQL.replace(" SELECT doc_id, cw AS crop_w", ", asg AS (SELECT doc_id, cw AS crop_w", 1) + """), s AS (SELECT doc_id, crop_w, crop_h, row_number() OVER (PARTITION BY crop_w, crop_h ORDER BY md5('e0:' || doc_id::VARCHAR), doc_id) - 1 AS rn, count(*) OVER (PARTITION BY crop_w, crop_h) AS n FROM asg),
 t AS (SELECT doc_id, crop_w, crop_h, (rn // 8)::INTEGER AS batch, (rn % 8)::INTEGER AS slot FROM s WHERE (rn // 8 + 1) * 8 <= n), hd AS (SELECT crop_w, crop_h, batch, row_number() OVER (ORDER BY md5('e0-batch:' || crop_w::VARCHAR || ':' || crop_h::VARCHAR || ':' || batch::VARCHAR)) - 1 AS batch_rank FROM t WHERE slot = 0)
 SELECT doc_id, crop_w, crop_h, batch, slot, batch_rank, batch_rank % 4 AS worker FROM t JOIN hd USING (crop_w, crop_h, batch)"""


def w11_resume(spark, d):
    """A run that stops after 20 batches and goes on: rows of the whole that neither part has, rows that both have,
    and rows of the parts that the whole has not."""
    with Scratch(spark, "resume") as s:
        whole = s.keep(_batches(spark, d).select("doc_id", "batch_rank", "slot"), "whole")
    done, rest = whole.where("batch_rank < 20"), curriculum.resume(whole, 20)
    keys = ["doc_id", "batch_rank", "slot"]
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return count(whole, "whole").join(count(done.unionByName(rest), "parts")).join(count(whole.join(done.unionByName(rest), keys, "left_anti"), "missing")).join(count(done.join(rest, keys, "left_semi"), "repeated"))


W11_R_SQL = "SELECT count(*) AS whole, count(*) AS parts, 0::BIGINT AS missing, 0::BIGINT AS repeated FROM (" + W11_SQL + ")"


def w12_rate(spark, d):
    return curriculum.failure_rate(table(spark, d, "events"), "hour")


W12_SQL = "SELECT date_trunc('hour', ts) AS bucket, count(*) AS n, count(*) FILTER (event_type = 'error') AS failed, round(avg((event_type = 'error')::INTEGER::DOUBLE), 6) AS rate FROM events GROUP BY 1"


def w12_placeholder(spark, d):
    return curriculum.substitute(table(spark, d, "events")).select("event_id", F.round("used", 6).alias("used"))


W12_P_SQL = "SELECT event_id, round(coalesce(CASE WHEN event_type <> 'error' THEN value END, last_value(CASE WHEN event_type <> 'error' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)), 6) AS used FROM events"

PROMPTS = {"real": "You describe a photograph.", "generated": "You describe a generated picture.", "illustration": "You describe an illustration.", "text_render": "You describe rendered text."}


def w28_prompts(spark, d):
    a = assets(spark, d)
    text = F.lit(None).cast("string")
    for k, v in PROMPTS.items():
        text = F.when(F.col("media_source") == k, v).otherwise(text)
    return a.select("doc_id", F.concat(text, F.lit(" Quality "), F.col("quality_tier").cast("string"), F.lit(" of 5.")).alias("prompt"))


W28_SQL = ASSETS_SQL + "SELECT doc_id, CASE media_source " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in PROMPTS.items()) + " END || ' Quality ' || quality_tier::VARCHAR || ' of 5.' AS prompt FROM assets"


def w28_chatml(spark, d):
    c = table(spark, d, "conversations").where("role IS NOT NULL AND text IS NOT NULL")
    part = F.concat(F.lit("<|im_start|>"), F.col("role"), F.lit("\n"), F.col("text"), F.lit("<|im_end|>\n"))
    return c.select("conv_id", F.struct("turn", part.alias("p")).alias("x")).groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list("x")), lambda x: x["p"]), "").alias("chat")).select("conv_id", F.md5("chat").alias("chat_md5"), F.char_length("chat").cast("long").alias("n"))


W28_C_SQL = "SELECT conv_id, md5(chat) AS chat_md5, length(chat)::BIGINT AS n FROM (SELECT conv_id, string_agg('<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10), '' ORDER BY turn, text) AS chat FROM conversations WHERE role IS NOT NULL AND text IS NOT NULL GROUP BY conv_id)"


def w29(spark, d):
    words = F.size(F.split("text", " "))
    stage = F.when(words <= 1, "word").when(F.col("text").contains("\n") & (words <= 60), "lines").when(words <= 60, "phrase").otherwise("paragraph")
    script = F.when(F.col("lang") == "en", "latin").otherwise("latin_extended")
    return table(spark, d, "documents").groupBy(stage.alias("stage"), script.alias("script")).agg(F.count(F.lit(1)).alias("n"))


W29_SQL = "SELECT CASE WHEN len(string_split(text, ' ')) <= 1 THEN 'word' WHEN contains(text, chr(10)) AND len(string_split(text, ' ')) <= 60 THEN 'lines' WHEN len(string_split(text, ' ')) <= 60 THEN 'phrase' ELSE 'paragraph' END AS stage, CASE WHEN lang = 'en' THEN 'latin' ELSE 'latin_extended' END AS script, count(*) AS n FROM documents GROUP BY 1, 2"


def w30_violations(spark, d):
    a = C.assemble(assets(spark, d)).withColumn("height", F.when(F.col("doc_id") % 97 == 0, 0).otherwise(F.col("height"))).withColumn("caption_sources", F.when(F.col("doc_id") % 89 == 0, F.slice("caption_sources", 1, 2)).otherwise(F.col("caption_sources")))
    return catalog.violations(a).select("doc_id", "violation")


W30_V_SQL = "SELECT doc_id, concat_ws('+', CASE WHEN doc_id % 97 = 0 THEN 'geometry' END, CASE WHEN doc_id % 89 = 0 THEN 'arrays' END) AS violation FROM documents WHERE doc_id % 97 = 0 OR doc_id % 89 = 0"


def w30_read(spark, d):
    with Scratch(spark, "snapshot") as s:
        path = catalog.publish(assets(spark, d).select("id", "doc_id", "width", "height", "quality_tier", "media_source"), s.root, 1)
    return catalog.open_run(spark, {"path": path, "where": ["quality_tier >= 4", "width >= 256"], "columns": ["doc_id", "width", "height"]})


W30_R_SQL = ASSETS_SQL + "SELECT doc_id, width, height FROM assets WHERE quality_tier >= 4 AND width >= 256"


def w30_diff(spark, d):
    a = assets(spark, d).select("doc_id", "raw_score", "quality_tier")
    b = a.where("doc_id % 50 <> 0").withColumn("raw_score", F.when(F.col("doc_id") % 10 == 3, F.col("raw_score") + 1).otherwise(F.col("raw_score"))).withColumn("quality_tier", quality.tier_fixed(F.col("raw_score")))
    return catalog.diff(a, b, "doc_id", ["raw_score", "quality_tier"])


_T = "1 + ({x} >= 5.0)::INTEGER + ({x} >= 7.0)::INTEGER + ({x} >= 8.5)::INTEGER + ({x} >= 9.2)::INTEGER"
W30_D_SQL = ASSETS_SQL + f", y AS (SELECT doc_id, raw_score AS a, quality_tier AS ta, CASE WHEN doc_id % 10 = 3 THEN raw_score + 1 ELSE raw_score END AS b FROM assets), z AS (SELECT *, {_T.format(x='b')} AS tb, doc_id % 50 <> 0 AS inb FROM y) SELECT 'raw_score' AS item, count(*) FILTER (inb AND a <> b) AS changed FROM z UNION ALL SELECT 'quality_tier', count(*) FILTER (inb AND ta <> tb) FROM z UNION ALL SELECT 'rows_added', 0 UNION ALL SELECT 'rows_removed', count(*) FILTER (NOT inb) FROM z"

# cosine coefficients, rounded, of rows (id, kind, grid), and their signs against the median
_DCT = """basis AS (SELECT v * 8 + u AS k, list(cos(pi() * (2 * (i // 8) + 1) * v / 16) * (CASE v WHEN 0 THEN sqrt(0.125::DOUBLE) ELSE 0.5 END) * cos(pi() * (2 * (i % 8) + 1) * u / 16) * (CASE u WHEN 0 THEN sqrt(0.125::DOUBLE) ELSE 0.5 END) ORDER BY i) AS b FROM range(8) a(v), range(8) c(u), range(64) d(i) GROUP BY v, u),
coef AS (SELECT id, kind, list(round(list_dot_product(grid, b), 9) ORDER BY k) AS f FROM grids, basis GROUP BY id, kind),
bits AS (SELECT id, kind, array_to_string(list_transform(f, lambda x: CASE WHEN x > (list_sort(f)[32] + list_sort(f)[33]) / 2 THEN '1' ELSE '0' END), '') AS bits FROM coef)"""
W04_PHASH_SQL = "WITH grids AS (SELECT vec_id AS id, 'own' AS kind, embedding::DOUBLE[] AS grid FROM embeddings), " + _DCT + " SELECT id AS vec_id, bits FROM bits"
W04_PLANTED_SQL = "WITH e AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings), grids AS (SELECT vec_id AS id, 'own' AS kind, x AS grid FROM e UNION ALL SELECT vec_id, 'exact', x FROM e UNION ALL SELECT vec_id, 'brighten', list_transform(x, lambda a: a + 0.1::DOUBLE) FROM e UNION ALL SELECT vec_id, 'noise', list_transform(range(64), lambda i: x[i + 1] + (((i * 7919 + vec_id) % 1009)::DOUBLE / 1009 - 0.5) * 1e-4) FROM e), " + _DCT + " SELECT c.kind, round(avg((hamming(o.bits, c.bits) <= 3)::INTEGER::DOUBLE), 6) AS recall FROM bits c JOIN bits o ON c.id = o.id AND o.kind = 'own' WHERE c.kind <> 'own' GROUP BY 1"
# weights of two features and a constant by Cramer's rule on the rounded sums
_DET = "({0}) * (({4}) * ({8}) - ({5}) * ({7})) - ({1}) * (({3}) * ({8}) - ({5}) * ({6})) + ({2}) * (({3}) * ({7}) - ({4}) * ({6}))"
_M = ["n + 1e-6", "l", "v", "l", "ll + 1e-6", "lv", "v", "lv", "vv + 1e-6"]


def _cramer(i: int) -> str:
    cells = list(_M)
    cells[i], cells[3 + i], cells[6 + i] = "t", "lt", "vt"
    return f"({_DET.format(*cells)}) / ({_DET.format(*_M)})"


W05_HEAD_SQL = ASSETS_SQL + ", j AS (SELECT letters, variety, quality FROM assets JOIN labels USING (doc_id)), s AS (SELECT round(sum(1.0::DOUBLE), 4) AS n, round(sum(letters), 4) AS l, round(sum(variety), 4) AS v, round(sum(letters * letters), 4) AS ll, round(sum(letters * variety), 4) AS lv, round(sum(variety * variety), 4) AS vv, round(sum(quality::DOUBLE), 4) AS t, round(sum(letters * quality), 4) AS lt, round(sum(variety * quality), 4) AS vt FROM j), " + f"w AS (SELECT {_cramer(0)} AS w0, {_cramer(1)} AS w1, {_cramer(2)} AS w2 FROM s) SELECT quality, round(avg(w0 + w1 * letters + w2 * variety), 4) AS mean_score, count(*) AS n FROM j, w GROUP BY 1"

QUERIES = {
    "w01_retention_funnel": (w01, W01_SQL),
    "w02_crawl_funnel": (w02, W02_SQL),
    "w03_exact_dedup": (w03_exact, W03_EXACT_SQL),
    "w03_near_pairs": (w03_pairs, SETS_SQL + " SELECT * FROM pairs"),
    "w03_clusters": (_clusters, CLUSTERS_SQL + " SELECT doc_id, cluster FROM cl"),
    "w03_removal_rates": (w03_rates, W03_RATES_SQL),
    "w03_survivors": (w03_survivors, W03_SURVIVORS_SQL),
    "w03_star": (w03_star, SETS_SQL + ", b AS (SELECT b AS node, arg_max(a, (jaccard, -a)) AS centre FROM pairs GROUP BY 1) SELECT doc_id, coalesce(centre, node) AS centre FROM sets JOIN nodes USING (s) LEFT JOIN b USING (node)"),
    "w03_two_stage": (w03_two_stage, W03_TWO_SQL),
    "w03_effective_diversity": (w03_diversity, W03_DIV_SQL),
    "w04_ahash_bits": (w04_ahash, W04_AHASH_SQL),
    "w04_phash_bits": (w04_phash, W04_PHASH_SQL),
    "w04_planted_recall": (w04_planted, W04_PLANTED_SQL),
    "w04_banded_recall": (w04_banded_recall, None),
    "w05_tier_sizes": (w05_tiers, W05_TIERS_SQL),
    "w05_head_gram": (w05_gram, W05_GRAM_SQL),
    "w05_head_scores": (w05_head, W05_HEAD_SQL),
    "w05_calibration": (w05_calibration, W05_CAL_SQL),
    "w05_tier_quantiles": (w05_quantile, W05_Q_SQL),
    "w05_synthetic_score": (w05_synth, W05_S_SQL),
    "w06_slices": (w06, W06_SQL),
    "w07_route_pages": (w07_pages, W07_P_SQL),
    "w07_route_vectors": (w07_vectors, W07_V_SQL),
    "w07_threshold_sweep": (w07_sweep, W07_SW_SQL),
    "w08_length_profile": (w08, W08_SQL),
    "w09_joint_view": (w09, W09_SQL),
    "w10_crops": (w10_crops, W10_C_SQL),
    "w10_assign": (w10_assign, W10_A_SQL),
    "w10_retained_vs_square": (w10_gain, W10_G_SQL),
    "w10_scale": (w10_scale, W10_S_SQL),
    "w11_batches": (w11_batches, W11_SQL),
    "w11_resume": (w11_resume, W11_R_SQL),
    "w12_failure_rate": (w12_rate, W12_SQL),
    "w12_alerts": (lambda s, d: curriculum.alerts(table(s, d, "events")), f"SELECT * FROM ({W12_SQL}) WHERE rate > 0.35"),
    "w12_placeholder": (w12_placeholder, W12_P_SQL),
    "w28_prompts": (w28_prompts, W28_SQL),
    "w28_chatml": (w28_chatml, W28_C_SQL),
    "w29_render_stages": (w29, W29_SQL),
    "w30_violations": (w30_violations, W30_V_SQL),
    "w30_manifest_read": (w30_read, W30_R_SQL),
    "w30_snapshot_diff": (w30_diff, W30_D_SQL),
}
