"""Validity tiers, caption handling, sampling and resumption: W1, W5-W7, W9-W12, W30 beyond the headline queries."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assetmill.operators import captions as C
from assetmill.operators import catalog, curriculum, quality, validate
from assetmill.plans.scratch import Scratch
from assetmill.sources.tables import table
from assetmill.workloads.curation import ASSETS_SQL, BUCKET_SQL, W07_P_SQL, W10_A_SQL, W11_SQL, _bucketed, _labelled, assets, pixels, w07_pages

GRID_SQL = "g AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings)"
_E = lambda i: f"e[{i + 1}]"


# --- tiers ---------------------------------------------------------------------------------------


def monochrome(s, d):
    v = F.round(validate.variance(F.col("grid")), 9)
    return pixels(s, d).select("vec_id", F.round(v, 6).alias("variance"), (v < 0.0154).alias("near_monochrome"))


def histogram(s, d):
    return validate.histogram(pixels(s, d), "grid")


def borders(s, d):
    return pixels(s, d).select("vec_id", F.round(validate.border_fraction(F.col("grid")), 6).alias("border"))


_EDGE = [r * 8 + c for r in range(8) for c in range(8) if r in (0, 7) or c in (0, 7)]


def orientation(s, d):
    tag = (F.col("vec_id") % 8 + 1).cast("int")
    p = pixels(s, d).select("vec_id", tag.alias("tag"), validate.normalise_orientation(F.col("grid"), tag).alias("up"))
    weighted = F.aggregate(F.transform("up", lambda x, i: x * (i + 1)), F.lit(0.0), lambda t, x: t + x)
    return p.select("vec_id", "tag", F.round(weighted, 5).alias("weighted"), (F.col("tag") >= 5).alias("sides_swapped"))


def watermark_lines(s, d):
    return validate.watermark_lines(table(s, d, "documents"))


LINES_SQL = "ln AS (SELECT doc_id, source, unnest(list_distinct(string_split(text, chr(10)))) AS line FROM documents), marks AS (SELECT source, line, count(*) AS documents FROM ln WHERE line <> '' GROUP BY 1, 2 HAVING count(*) >= 3)"


def blur(s, d):
    return pixels(s, d).select("vec_id", F.round(validate.blur_score(F.col("grid")), 6).alias("blur"))


_BLOCKS = " + ".join("((" + " + ".join(_E((r + i) * 8 + c + j) for i in (0, 1) for j in (0, 1)) + ") / 2) ** 2" for r in range(0, 8, 2) for c in range(0, 8, 2))


def hard_filters(s, d):
    docs = table(s, d, "documents")
    return quality.hard_filters(docs, validate.watermark_lines(docs))


_ODD = r"""length(regexp_replace(text, '[\p{L}\p{N} \t\n\r.,;:!?''"()-]', '', 'g'))::DOUBLE / greatest(length(text), 1) > 0.1"""


def chrome(s, d):
    share = F.round(quality.chrome_share(F.col("html")), 6)
    return table(s, d, "pages").select("page_id", share.alias("chrome"), (share > quality.MOST_CHROME).alias("dropped"))


_PART = lambda p: f"strlen(regexp_extract(html, '(?s){p}', 0))"
CHROME_SQL = "WITH c AS (SELECT page_id, round((" + " + ".join(_PART(p) for p in ("<nav>.*?</nav>", '<div class="ad">.*?</div>', "<footer>.*?</footer>")) + ")::DOUBLE / greatest(strlen(html), 1), 6) AS chrome FROM pages) SELECT page_id, chrome, chrome > 0.3 AS dropped FROM c"


def safety(s, d):
    """Rows that a scorer, here the given labels, calls unsafe; a model goes in its place as a column."""
    flagged = table(s, d, "labels").where("toxic = 1").select(F.col("doc_id").alias("_d"), F.lit(1.0).alias("_unsafe"))
    scored = assets(s, d).select("doc_id").join(flagged, F.col("doc_id") == F.col("_d"), "left")
    return scored.select("doc_id", (F.coalesce("_unsafe", F.lit(0.0)) < 0.5).alias("safe"))


def tier_counts(s, d):
    w, h = F.col("width"), F.col("height")
    tiers = [("geometry", validate.positive_geometry(w, h) & validate.min_side(w, h)), ("aspect", validate.aspect_ok(w, h, 8.0)), ("decodable", validate.decodable(F.col("text"))), ("symbols", quality.odd_share(F.col("text")) <= quality.MOST_ODD)]
    return validate.tier_counts(assets(s, d), tiers)


_T = ("width > 0 AND height > 0 AND least(width, height) >= 64", "greatest(width::DOUBLE / height, height::DOUBLE / width) <= 8.0", "text IS NOT NULL AND length(text) > 0 AND NOT regexp_matches(substr(text, 1, 4), '[\\x00-\\x08]')", f"NOT ({_ODD})")
TIERS_SQL = ASSETS_SQL + " UNION ALL ".join(f"SELECT '{n}' AS tier, count(*) AS kept FROM assets WHERE " + " AND ".join(_T[: i + 1]) for i, n in enumerate(("geometry", "aspect", "decodable", "symbols")))


# --- metadata ------------------------------------------------------------------------------------


def attached(s, d):
    """Label annotations beside the assets' keys; no payload is read."""
    more = table(s, d, "labels").select(F.concat(F.lit("d"), F.col("doc_id").cast("string")).alias("id"), F.col("quality").alias("label_quality"))
    return catalog.attach(assets(s, d).select("id", "width"), more)


def pair_supply(s, d):
    return catalog.pair_supply(C.assemble(assets(s, d)))


def core_table(s, d):
    full = catalog.core_table(C.assemble(_bucketed(s, d)))
    return catalog.enforce(full).select("id", "media_path", "width", "height", F.size("captions").alias("captions"), "media_source", "aesthetic_score", "quality_tier", "episodic_bucket", "sha256")


def evolution(s, d):
    old = table(s, d, "documents").schema
    new = table(s, d, "documents").withColumn("licence", F.lit("x")).withColumn("n_chars", F.col("n_chars").cast("int")).drop("lang").schema
    return s.createDataFrame(catalog.check_evolution(old, new), "field string, verdict string")


# --- captions ------------------------------------------------------------------------------------


def captioner(s, d):
    a = table(s, d, "documents")
    return a.select("doc_id", C.pick_captioner(a).alias("captioner"))


def requests(s, d):
    """What a captioner is asked for each caption that is not kept, taken apart again."""
    rows = w07_pages(s, d).withColumn("locator", F.concat(F.lit("page/"), F.col("page_id").cast("string")))
    rows = rows.withColumn("request", C.request(F.col("route"), F.col("locator"), F.col("source"), F.concat(F.lit("text of "), F.col("source"))))
    part = lambda k: F.get_json_object("request", f"$.{k}").alias(k)
    return rows.select("page_id", "source", "route", part("pixels"), part("web_text"), part("provenance"))


REQUEST_SQL = f"SELECT page_id, source, route, CASE WHEN route <> 'preserve' THEN 'page/' || page_id::VARCHAR END AS pixels, CASE route WHEN 'refine' THEN 'text of ' || source END AS web_text, CASE route WHEN 'synthesize' THEN source END AS provenance FROM ({W07_P_SQL})"


def appended(s, d):
    a = C.assemble(assets(s, d)).withColumn("better", F.concat(F.lit("A picture: "), F.get("captions", F.lit(1))))
    a = C.append(a, "better", "refined")
    return a.select("doc_id", F.size("captions").alias("captions"), F.element_at("caption_sources", -1).alias("last_source"), F.element_at("caption_lengths", -1).alias("last_length"), F.md5(F.get("captions", F.lit(1))).alias("kept_md5"))


MIX = {"crawl": 0.1, "short": 0.2, "medium": 0.3, "detailed": 0.4}


def chosen(s, d):
    return C.choose(assets(s, d), MIX, "e1").select("doc_id", "chosen")


def uniform_sql(seed: str, key: str) -> str:
    return f"(('0x' || substr(md5('{seed}:' || {key}), 1, 13))::BIGINT::DOUBLE / 4503599627370496.0::DOUBLE)"


def pick_sql(u: str, weights: dict[str, float]) -> str:
    """The key whose share of the weights, one after the other, a uniform number falls into."""
    total, at, arms = sum(weights.values()), 0.0, []
    for k, w in weights.items():
        at += w / total
        arms.append(f"WHEN {u} < {at!r}::DOUBLE THEN '{k}'")
    return f"CASE {' '.join(arms[:-1])} ELSE '{list(weights)[-1]}' END"


def caption_policies(s, d):
    """Captions that go to a captioner if all are kept, all are written anew, or each is routed by its alignment."""
    r = w07_pages(s, d)
    return r.agg(F.count(F.lit(1)).alias("captions"), F.lit(0).cast("long").alias("keep_all"), F.count(F.lit(1)).alias("recaption_all"), F.count_if(F.col("route") != "preserve").alias("routed"), F.count_if(F.col("route") == "synthesize").alias("without_web_text"))


def granularity(s, d):
    """One caption against all of them: words a row that training sees."""
    a = C.assemble(assets(s, d))
    return a.agg(F.round(F.avg(F.get("caption_lengths", F.lit(0)).cast("double")), 6).alias("one_caption"), F.round(F.avg(F.aggregate("caption_lengths", F.lit(0), lambda t, x: t + x).cast("double")), 6).alias("all_captions"), *(F.sum(F.get("caption_lengths", F.lit(i)).cast("long")).alias(f"{n}_words") for i, n in enumerate(("crawl", "short", "medium", "detailed"))))


CAPTIONS_SQL = ASSETS_SQL + r", c AS (SELECT doc_id, media_source, raw_score, variety, text, [string_split(text, chr(10))[1], string_split(text, '.')[1], array_to_string(string_split(text, ' ')[1:60], ' '), array_to_string(string_split(text, ' ')[1:250], ' ')] AS cs FROM assets), l AS (SELECT *, list_transform(cs, lambda t: len(string_split(t, ' '))::INTEGER) AS n FROM c)"


def caption_feedback(s, d):
    a = C.assemble(assets(s, d)).where("media_source <> 'real'")
    return a.select("doc_id", quality.synthetic_score_with_captions(a).alias("score"))


# --- curriculum ----------------------------------------------------------------------------------


def tier_weights(s, d):
    """Share of draws of each tier under weights for all tiers, and under the single best tier."""
    w = curriculum.tier_weights()
    n = assets(s, d).groupBy("quality_tier").agg(F.count(F.lit(1)).alias("n"))
    best = n.agg(F.max("quality_tier").alias("best"))
    mass = F.col("n") * curriculum.by_weight(F.col("quality_tier"), w)
    total = n.agg(F.sum(mass).alias("total"))
    return n.join(F.broadcast(total)).join(F.broadcast(best)).select("quality_tier", "n", F.round(mass / F.col("total"), 6).alias("weighted"), (F.col("quality_tier") == F.col("best")).cast("double").alias("best_only"))


CUTS = [2.0, 3.0, 4.0]


def predicates(s, d):
    """Rows of each score range, read by its stored predicate."""
    a = assets(s, d).withColumn("rank_score", curriculum.score(F.col("quality_tier"), F.col("resolution")))
    return a.agg(*(F.count_if(F.expr(p)).alias(f"r{i}") for i, p in enumerate(curriculum.bucket_predicates(CUTS, "rank_score"))))


def mixtures(s, d):
    """Bucket weights at the progress that each line's discount stands for, and how many lines are there."""
    at = table(s, d, "lineitem").groupBy(F.round(F.col("l_discount") * 10, 1).alias("progress")).agg(F.count(F.lit(1)).alias("lines"))
    w = at.select("progress", "lines", F.posexplode(F.array(*curriculum.mixture(F.col("progress")))).alias("k", "w"))
    return w.select("progress", (F.col("k") + 1).alias("bucket"), F.round("w", 6).alias("weight"), "lines")


_MIX_W = "0.02 + 0.84::DOUBLE * ((1 - p) * (9 - k) + p * k) / 36"


def sampled(s, d):
    """Fifty assets drawn by the mixture halfway through training."""
    weights = F.get(F.array(*map(F.lit, curriculum.mixture(0.25))), F.col("episodic_bucket") - 1)
    return curriculum.sample(_bucketed(s, d), weights, 50, "m1").select("doc_id", "episodic_bucket")


def tasks(s, d):
    """Training tasks by phase: how many assets each gets."""
    a, out = assets(s, d), None
    for phase, weights in curriculum.TASKS.items():
        task = curriculum.assign_task(C.uniform(F.lit(f"task-{phase}"), F.col("id")), weights)
        one = a.groupBy(task.alias("task")).agg(F.count(F.lit(1)).alias("n")).select(F.lit(phase).alias("phase"), "task", "n")
        out = one if out is None else out.union(one)
    return out


TASKS_SQL = ASSETS_SQL + " UNION ALL ".join(f"SELECT '{p}' AS phase, {pick_sql(uniform_sql(f'task-{p}', 'id'), w)} AS task, count(*) AS n FROM assets GROUP BY 2" for p, w in curriculum.TASKS.items())


def policy(s, d):
    """Assets that each phase's control row lets in."""
    a = assets(s, d).select("quality_tier", "width", "height")
    p = curriculum.policy(s)
    fits = (F.col("quality_tier") >= F.col("least_tier")) & (F.col("width").cast("long") * F.col("height") * 4 >= F.col("geometry").cast("long") * F.col("geometry"))
    return a.groupBy("quality_tier", "width", "height").agg(F.count(F.lit(1)).alias("rows")).join(F.broadcast(p), fits).groupBy("phase", "geometry", "granularity", "supervision").agg(F.sum("rows").alias("n"))


def complex_filter(s, d):
    spec = {"match": {"text": r"[.]"}, "without": {"text": "http"}, "drop_captions": "crawl|medium"}
    return curriculum.complex_filter(C.assemble(assets(s, d)), spec).select("doc_id", F.size("captions").alias("captions"), F.array_join("caption_sources", ",").alias("sources"))


def crop_boxes(s, d):
    a = curriculum.assign_crop(assets(s, d).select("doc_id", "width", "height"), curriculum.crops(256))
    x, y, w, h = curriculum.crop_box(F.col("width"), F.col("height"), F.col("crop_w"), F.col("crop_h"))
    return a.select("doc_id", x.cast("long").alias("x"), y.cast("long").alias("y"), w.cast("long").alias("w"), h.cast("long").alias("h"))


def short_batches(s, d):
    """Batches with and without a short last one in each bucket."""
    out = None
    with Scratch(s, "short") as scratch:
        a = curriculum.assign_crop(assets(s, d), curriculum.crops(256)).select("doc_id", "crop_w", "crop_h")
        a = scratch.keep(a, "assigned")
        for name, drop in (("drop_last", True), ("keep_short", False)):
            b = curriculum.batches(a, ["crop_w", "crop_h"], "doc_id", 8, "e0", scratch, drop)
            one = b.agg(F.lit(name).alias("tail"), F.count(F.lit(1)).alias("rows"), F.count_if(F.col("slot") == 0).alias("batches"))
            out = one if out is None else out.union(one)
    return out


SHORT_SQL = W10_A_SQL.replace(" SELECT doc_id, cw AS crop_w", ", asg AS (SELECT doc_id, cw AS crop_w", 1) + "), k AS (SELECT crop_w, crop_h, count(*) AS n FROM asg GROUP BY 1, 2) SELECT 'drop_last' AS tail, sum(n - n % 8)::BIGINT AS rows, sum(n // 8)::BIGINT AS batches FROM k UNION ALL SELECT 'keep_short', sum(n)::BIGINT, sum((n + 7) // 8)::BIGINT FROM k"


def workers(s, d):
    """Batches of each worker; no batch has two."""
    from assetmill.workloads.curation import _batches

    return _batches(s, d).where("slot = 0").groupBy(F.col("worker").cast("long").alias("worker")).agg(F.count(F.lit(1)).alias("batches"))


def placeholder_bucket(s, d):
    """A failed fetch takes the last success of its own bucket of shapes."""
    e = table(s, d, "events").withColumn("shape", F.pmod(F.col("user_id"), F.lit(7)))
    return curriculum.substitute(e, ["shape"]).select("event_id", "shape", F.round("used", 6).alias("used"))


PLACE_SQL = "SELECT event_id, user_id % 7 AS shape, round(coalesce(CASE WHEN event_type <> 'error' THEN value END, last_value(CASE WHEN event_type <> 'error' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id % 7 ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)), 6) AS used FROM events"


def isotonic(s, d):
    """Labels as a rising step function of the score: bins pooled until their means do not fall."""
    bins = quality.calibration(_labelled(s, d), "raw_score", "quality").orderBy("bin").collect()  # ten rows at most
    pooled = quality.pool_adjacent([r.mean_label for r in bins], [r.n for r in bins])
    return s.createDataFrame([(r.bin, r.n, round(p, 6)) for r, p in zip(bins, pooled)], "bin int, n long, pooled double")


def tier_sketch(s, d):
    """Tiers by cut points from a quantile sketch against the exact ones: rows that they place alike, and in a
    neighbouring tier."""
    a = assets(s, d).select("doc_id", "raw_score", "media_source")
    exact = quality.tier_quantile(a, "raw_score", "media_source", "doc_id").select("doc_id", F.col("tier").alias("exact"))
    both = quality.tier_sketch(a, "raw_score", "media_source").select("doc_id", "tier").join(exact, "doc_id")
    return both.agg(F.count(F.lit(1)).alias("rows"), F.count_if(F.abs(F.col("tier") - F.col("exact")) <= 1).alias("near"))


def merged_streams(s, d):
    a = assets(s, d)
    real = quality.floor(a.where("media_source = 'real'")).select("doc_id", "quality_tier")
    synthetic = a.where("media_source <> 'real'").select("doc_id", "quality_tier")
    return quality.merge_streams(real, synthetic)


_SYN = "round(10 * (0.3::DOUBLE * least(1.0::DOUBLE, ln(1 + length(text)::DOUBLE) / 10) + 0.4::DOUBLE * variety + 0.3::DOUBLE * CASE media_source WHEN 'generated' THEN 0.5 WHEN 'illustration' THEN 0.7 ELSE 0.6 END), 6)"
_BOX = "least(width::DOUBLE / crop_w, height::DOUBLE / crop_h)"

QUERIES = {
    "w01_monochrome": (monochrome, "WITH " + GRID_SQL + ", v AS (SELECT vec_id, round(list_aggregate(e, 'var_pop'), 9) AS v FROM g) SELECT vec_id, round(v, 6) AS variance, v < 0.0154 AS near_monochrome FROM v"),
    "w01_histogram": (histogram, "SELECT least(7, greatest(0, floor((x + 0.5::DOUBLE) / 0.125::DOUBLE)))::INTEGER AS bin, count(*) AS n FROM (SELECT unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY 1"),
    "w01_borders": (borders, "WITH " + GRID_SQL + " SELECT vec_id, round((" + " + ".join(f"{_E(i)} * {_E(i)}" for i in _EDGE) + ") / list_dot_product(e, e), 6) AS border FROM g"),
    "w01_orientation": (orientation, "WITH " + GRID_SQL + ", u AS (SELECT vec_id, (vec_id % 8 + 1)::INTEGER AS tag, list_transform([" + ", ".join(map(str, [validate.orientation_map(t) for t in range(1, 9)])) + "][vec_id % 8 + 1], lambda i: e[i + 1]) AS up FROM g) SELECT vec_id, tag, round(list_dot_product(up, range(1, 65)::DOUBLE[]), 5) AS weighted, tag >= 5 AS sides_swapped FROM u"),
    "w01_watermark_lines": (watermark_lines, "WITH " + LINES_SQL + " SELECT source, line, documents FROM marks"),
    "w01_blur": (blur, "WITH " + GRID_SQL + f" SELECT vec_id, round(1 - ({_BLOCKS}) / list_dot_product(e, e), 6) AS blur FROM g"),
    "w01_hard_filters": (hard_filters, "WITH " + LINES_SQL + f", hit AS (SELECT DISTINCT doc_id FROM ln JOIN marks ON ln.source IS NOT DISTINCT FROM marks.source AND ln.line = marks.line), f AS (SELECT doc_id, doc_id IN (SELECT doc_id FROM hit) AS watermark, coalesce({_ODD}, false) AS artifacts FROM documents) SELECT *, watermark OR artifacts AS dropped FROM f"),
    "w01_chrome": (chrome, CHROME_SQL),
    "w01_safety": (safety, "SELECT doc_id, doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1) AS safe FROM documents"),
    "w01_tier_counts": (tier_counts, TIERS_SQL),
    "w05_calibration_isotonic": (isotonic, None),
    "w05_caption_feedback": (caption_feedback, CAPTIONS_SQL + f" SELECT doc_id, round(0.8::DOUBLE * {_SYN} + 2 * len(list_distinct(cs)) / 4.0::DOUBLE, 6) AS score FROM l WHERE media_source <> 'real'"),
    "w05_merged_streams": (merged_streams, ASSETS_SQL + "SELECT doc_id, quality_tier, CASE WHEN media_source = 'real' THEN 'real' ELSE 'synthetic' END AS stream FROM assets WHERE media_source <> 'real' OR aesthetic_score >= 5.0"),
    "w05_tier_sketch": (tier_sketch, "SELECT count(*) AS rows, count(*) AS near FROM documents"),
    "w06_tier_weights": (tier_weights, ASSETS_SQL + "SELECT quality_tier, n, round(n * greatest(0, quality_tier - 1)::DOUBLE / sum(n * greatest(0, quality_tier - 1)) OVER (), 6) AS weighted, (quality_tier = max(quality_tier) OVER ())::INTEGER::DOUBLE AS best_only FROM (SELECT quality_tier, count(*) AS n FROM assets GROUP BY 1)"),
    "w07_captioner": (captioner, r"SELECT doc_id, CASE WHEN length(regexp_replace(text, '[\p{L} \t\n\r.,]', '', 'g'))::DOUBLE / greatest(length(text), 1) > 0.05 THEN 'precise' ELSE 'fast' END AS captioner FROM documents"),
    "w07_requests": (requests, REQUEST_SQL),
    "w07_append": (appended, ASSETS_SQL + "SELECT doc_id, 5 AS captions, 'refined' AS last_source, len(string_split('A picture: ' || string_split(text, '.')[1], ' '))::INTEGER AS last_length, md5(string_split(text, '.')[1]) AS kept_md5 FROM assets"),
    "w07_choose": (chosen, ASSETS_SQL + f"SELECT doc_id, {pick_sql(uniform_sql('e1', 'id'), MIX)} AS chosen FROM assets"),
    "w07_policies": (caption_policies, f"SELECT count(*) AS captions, 0::BIGINT AS keep_all, count(*) AS recaption_all, count(*) FILTER (route <> 'preserve') AS routed, count(*) FILTER (route = 'synthesize') AS without_web_text FROM ({W07_P_SQL})"),
    "w08_granularity": (granularity, CAPTIONS_SQL + " SELECT round(avg(n[1]::DOUBLE), 6) AS one_caption, round(avg(list_sum(n)::DOUBLE), 6) AS all_captions, " + ", ".join(f"sum(n[{i + 1}])::BIGINT AS {k}_words" for i, k in enumerate(("crawl", "short", "medium", "detailed"))) + " FROM l"),
    "w09_predicates": (predicates, ASSETS_SQL + ", r AS (SELECT quality_tier + 0.5::DOUBLE * resolution AS x FROM assets) SELECT count(*) FILTER (x < 2) AS r0, count(*) FILTER (x >= 2 AND x < 3) AS r1, count(*) FILTER (x >= 3 AND x < 4) AS r2, count(*) FILTER (x >= 4) AS r3 FROM r"),
    "w09_mixture": (mixtures, f"SELECT p AS progress, k::INTEGER AS bucket, round({_MIX_W}, 6) AS weight, lines FROM (SELECT round(l_discount * 10, 1) AS p, count(*) AS lines FROM lineitem GROUP BY 1) a, range(1, 9) b(k)"),
    "w09_sample": (sampled, BUCKET_SQL + f", w AS (SELECT doc_id, id, episodic_bucket, {_MIX_W.replace('p', '0.25::DOUBLE').replace('k', 'episodic_bucket')} AS w FROM b) SELECT doc_id, episodic_bucket FROM w ORDER BY -ln(greatest({uniform_sql('m1', 'id')}, 1e-15)) / w, id LIMIT 50"),
    "w09_tasks": (tasks, TASKS_SQL),
    "w09_policy": (policy, ASSETS_SQL + ", p AS (SELECT * FROM (VALUES " + ", ".join(str(r) for r in curriculum.POLICY) + ") v(phase, geometry, least_tier, granularity, supervision)) SELECT phase, geometry::INTEGER AS geometry, granularity, supervision, count(*) AS n FROM assets JOIN p ON quality_tier >= least_tier AND width::BIGINT * height * 4 >= geometry::BIGINT * geometry GROUP BY 1, 2, 3, 4"),
    "w09_complex_filter": (complex_filter, ASSETS_SQL + "SELECT doc_id, 2 AS captions, 'short,detailed' AS sources FROM assets WHERE contains(text, '.') AND NOT contains(text, 'http')"),
    "w10_crop_boxes": (crop_boxes, W10_A_SQL.replace(" SELECT doc_id, cw AS crop_w", ", asg AS (SELECT doc_id, cw AS crop_w", 1) + f"), z AS (SELECT doc_id, width, height, floor(crop_w * {_BOX})::BIGINT AS w, floor(crop_h * {_BOX})::BIGINT AS h FROM asg JOIN assets USING (doc_id)) SELECT doc_id, floor((width - w) / 2.0)::BIGINT AS x, floor((height - h) / 2.0)::BIGINT AS y, w, h FROM z"),
    "w11_short_batches": (short_batches, SHORT_SQL),
    "w11_workers": (workers, "SELECT worker, count(*) AS batches FROM (" + W11_SQL + ") WHERE slot = 0 GROUP BY 1"),
    "w12_placeholder_bucket": (placeholder_bucket, PLACE_SQL),
    "w30_attach": (attached, ASSETS_SQL + "SELECT id, width, l.quality AS label_quality FROM assets a LEFT JOIN labels l ON a.doc_id = l.doc_id"),
    "w30_pair_supply": (pair_supply, "SELECT count(*) AS assets, 4 * count(*) AS pairs, 4.0::DOUBLE AS captions_per_asset FROM documents"),
    "w30_core_table": (core_table, BUCKET_SQL + " SELECT id, media_path, width, height, 4 AS captions, media_source, aesthetic_score, quality_tier, episodic_bucket, sha256 FROM b WHERE width > 0 AND height > 0"),
    "w30_evolution": (evolution, "SELECT * FROM (VALUES ('doc_id', 'ok'), ('lang', 'missing'), ('licence', 'added'), ('n_chars', 'retyped'), ('source', 'ok'), ('text', 'ok')) v(field, verdict)"),
}
