"""Render specifications, allocation maps, remaining axis stand-ins and network pieces."""

from __future__ import annotations

from pyspark.sql import functions as F

from assetmill.operators import allocation, latents, mathkit, textrender
from assetmill.plans.bounded import at_most
from assetmill.sources.tables import table

#: Labels up to which all centroids travel together in one row.
MOST_LABELS = 4096
_add = lambda s, x: s + x


def render_specs(s, d):
    return textrender.specs(table(s, d, "part").select("p_partkey"), "p_partkey")


def render_rows(s, d):
    return textrender.rows(table(s, d, "part").select("p_partkey", "p_name"), "p_partkey", "p_name")


def scripts(s, d):
    return table(s, d, "documents").groupBy(textrender.script(F.col("text")).alias("script")).agg(F.count(F.lit(1)).alias("n"))


def glyphs(s, d):
    return table(s, d, "part").select("p_partkey", (8 * F.char_length("p_name")).alias("width"), textrender.ink(F.col("p_name")).cast("long").alias("ink"))


def doubles(s, d):
    return table(s, d, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("x"))


def upsampled(s, d):
    up = doubles(s, d).select("vec_id", allocation.upsample(F.col("x"), 8, 2).alias("u"))
    weighted = F.aggregate(F.transform("u", lambda v, i: v * (i + 1)), F.lit(0.0), _add)
    return up.select("vec_id", F.round(F.get("u", F.lit(0)), 5).alias("corner"), F.round(F.get("u", F.lit(17)), 5).alias("inner"), F.round(weighted, 3).alias("weighted"))


UPSAMPLE_SQL = """WITH k AS (SELECT k, greatest(0.0::DOUBLE, least(7.0::DOUBLE, (k // 16 + 0.5::DOUBLE) / 2 - 0.5)) AS y, greatest(0.0::DOUBLE, least(7.0::DOUBLE, (k % 16 + 0.5::DOUBLE) / 2 - 0.5)) AS x FROM range(256) t(k)),
n AS (SELECT k, floor(y)::INTEGER AS r, least(floor(y)::INTEGER + 1, 7) AS r1, y - floor(y) AS v, floor(x)::INTEGER AS c, least(floor(x)::INTEGER + 1, 7) AS c1, x - floor(x) AS h FROM k),
u AS (SELECT vec_id, k, (e[r * 8 + c + 1] * (1 - h) + e[r * 8 + c1 + 1] * h) * (1 - v) + (e[r1 * 8 + c + 1] * (1 - h) + e[r1 * 8 + c1 + 1] * h) * v AS u FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings), n)
SELECT vec_id, round(max(u) FILTER (k = 0), 5) AS corner, round(max(u) FILTER (k = 17), 5) AS inner, round(sum(u * (k + 1)), 3) AS weighted FROM u GROUP BY 1"""


def sharpness(s, d):
    """How uneven each map is, and how it goes with the edges of the picture it lies on."""
    m = doubles(s, d).select("vec_id", "x", allocation.gradient(F.col("x"), 8).alias("g"), allocation.gini(F.transform("x", F.exp)).alias("gini"))
    cells = m.select("vec_id", "gini", F.explode(F.arrays_zip("x", "g")).alias("c"))
    return cells.groupBy("vec_id").agg(F.round(F.var_pop("c.x"), 5).alias("variance"), F.round(F.first("gini"), 5).alias("gini"), F.round(F.corr("c.x", "c.g"), 5).alias("edges"))


SHARP_SQL = """WITH c AS (SELECT vec_id, i, i // 8 AS r, i % 8 AS c, embedding[i + 1]::DOUBLE AS v, embedding::DOUBLE[] AS e FROM embeddings, range(64) t(i)),
g AS (SELECT vec_id, v, sqrt(pow(e[r * 8 + least(c + 1, 7) + 1] - e[r * 8 + greatest(c - 1, 0) + 1], 2) + pow(e[least(r + 1, 7) * 8 + c + 1] - e[greatest(r - 1, 0) * 8 + c + 1], 2)) AS g, row_number() OVER (PARTITION BY vec_id ORDER BY v, i) AS p FROM c)
SELECT vec_id, round(var_pop(v), 5) AS variance, round(sum((2 * p - 65) * exp(v)) / (64 * sum(exp(v))), 5) AS gini, round(corr(v, g), 5) AS edges FROM g GROUP BY 1"""


def centroids(s, d):
    parts = doubles(s, d).select("label", F.posexplode("x").alias("i", "v")).groupBy("label", "i").agg(F.avg("v").alias("m"))
    return parts.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda p: p["m"]).alias("centre"))


def cosine(a, b):
    return mathkit.dot(a, b) / F.sqrt(mathkit.dot(a, a) * mathkit.dot(b, b))


def axis_alignment(s, d):
    near = doubles(s, d).join(centroids(s, d), "label")
    return near.agg(F.round(F.avg((1 + cosine(F.col("x"), F.col("centre"))) / 2), 5).alias("alignment"))


def axis_style(s, d):
    """Share of vectors whose nearest centroid is their label's; of equal ones the smaller label."""
    c = centroids(s, d)
    if not at_most(c, MOST_LABELS):
        raise ValueError(f"more than {MOST_LABELS} labels")
    packed = c.agg(F.collect_list(F.struct("label", "centre")).alias("all"))
    best = F.array_max(F.transform("all", lambda p: F.struct(F.round(cosine(F.col("x"), p["centre"]), 9).alias("s"), (-p["label"]).alias("l"))))
    return doubles(s, d).crossJoin(F.broadcast(packed)).agg(F.round(F.avg((-best["l"] == F.col("label")).cast("int")), 6).alias("style"))


CENTRE_SQL = "WITH m AS (SELECT label, i, avg(embedding[i]::DOUBLE) AS m FROM embeddings, range(1, 65) t(i) GROUP BY label, i), c AS (SELECT label, list(m ORDER BY i) AS centre FROM m GROUP BY label)"


def axis_reasoning(s, d):
    """Share of an answer's words that its question has, over turns that follow each other."""
    t = table(s, d, "conversations").select("conv_id", "turn", "role", F.array_distinct(F.split(F.lower("text"), " ")).alias("w"))
    q, a = t.where("role = 'user'").select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("w").alias("q")), t.where("role = 'assistant'").select("conv_id", "turn", F.col("w").alias("a"))
    return q.join(a, ["conv_id", "turn"]).agg(F.round(F.avg(F.size(F.array_intersect("q", "a")) / F.size("a")), 6).alias("reasoning"), F.count(F.lit(1)).alias("turns"))


REASON_SQL = "WITH t AS (SELECT conv_id, turn, role, list_distinct(string_split(lower(text), ' ')) AS w FROM conversations) SELECT round(avg(len(list_intersect(q.w, a.w)) / len(a.w)), 6) AS reasoning, count(*) AS turns FROM t q JOIN t a ON q.conv_id = a.conv_id AND q.turn + 1 = a.turn AND q.role = 'user' AND a.role = 'assistant'"


def timesteps(s, d):
    """Embedding of each line's time step, which its quantity stands for, and how many lines are there."""
    at = table(s, d, "lineitem").groupBy((F.col("l_quantity").cast("long") - 1).alias("step")).agg(F.count(F.lit(1)).alias("lines"))
    t = at.select("step", "lines", F.posexplode(mathkit.timestep_embedding(F.col("step") / 49, 16)).alias("i", "v"))
    return t.select("step", F.col("i").cast("long").alias("i"), F.round("v", 6).alias("v"), "lines")


STEP_SQL = "SELECT step, i, round(CASE WHEN i < 8 THEN cos(1000 * (step / 49.0::DOUBLE) * pow(10000.0::DOUBLE, -(i % 8) / 8.0::DOUBLE)) ELSE sin(1000 * (step / 49.0::DOUBLE) * pow(10000.0::DOUBLE, -(i % 8) / 8.0::DOUBLE)) END, 6) AS v, lines FROM (SELECT l_quantity::BIGINT - 1 AS step, count(*) AS lines FROM lineitem GROUP BY 1) a, range(16) b(i)"

# Standard deviations at the start, by kind of parameter.
START = {"linear": 0.02, "router": 0.006, "modulation": 0.0}


def initialised(s, d):
    """Spread and largest value of drawn parameters; for routers, the entropy of 64 experts' softmax over log 64."""
    kinds = None
    for seed, (kind, sigma) in enumerate(START.items()):
        draw = mathkit.truncated_normal(F.col("id"), sigma, seed)
        part = s.range(64 * 1024).select(F.lit(kind).alias("kind"), F.floor(F.col("id") / 64).alias("token"), draw.alias("w"))
        kinds = part if kinds is None else kinds.unionByName(part)
    rows = kinds.groupBy("kind", "token").agg(F.sum("w").alias("s"), F.sum(F.col("w") * F.col("w")).alias("q"), F.max(F.abs("w")).alias("top"), F.log(F.sum(F.exp("w"))).alias("z"), F.sum(F.col("w") * F.exp("w")).alias("t"), F.sum(F.exp("w")).alias("e"))
    return rows.groupBy("kind").agg(F.sqrt(F.sum("q") / (64 * F.count(F.lit(1)))).alias("spread"), F.max("top").alias("largest"), (F.avg(F.col("z") - F.col("t") / F.col("e")) / F.log(F.lit(64.0))).alias("evenness"))


def precision_gap(s, d):
    """Largest differences of flow and wavelet loss between single and double precision."""
    e = table(s, d, "embeddings").select("embedding", F.transform("embedding", lambda v, i: (v + F.sin(i.cast("double")) / 10).cast("float")).alias("noisy"))
    gap = lambda f: F.max(F.abs(f("float").cast("double") - f("double")))
    flow = lambda kind: F.aggregate(F.zip_with(F.col("embedding").cast(f"array<{kind}>"), F.col("noisy").cast(f"array<{kind}>"), lambda a, b: ((a - b) * (a - b)).cast(kind)), F.lit(0).cast(kind), lambda x, y: (x + y).cast(kind)) / F.lit(64).cast(kind)
    return e.agg(gap(flow).alias("flow"), F.max(F.abs(mathkit.wavelet_loss(F.col("embedding"), F.col("noisy")) - mathkit.wavelet_loss(F.col("embedding").cast("array<double>"), F.col("noisy").cast("array<double>")))).alias("wavelet"))


def latent_round_trip(s, d):
    codec = latents.Identity()
    z = latents.apply(doubles(s, d), "vec_id", "x", codec)
    return latents.apply(z, "vec_id", "x", codec, back=True).select("vec_id", F.round(F.aggregate("x", F.lit(0.0), _add), 5).alias("total"))


SCRIPT_SQL = r"SELECT CASE WHEN regexp_matches(text, '[\p{Han}\p{Hiragana}\p{Katakana}\p{Hangul}]') THEN 'logographic' WHEN regexp_matches(text, '[\p{Cyrillic}\p{Greek}\p{Arabic}\p{Hebrew}\p{Devanagari}]') THEN 'other_alphabet' WHEN regexp_matches(text, '[\x{00C0}-\x{024F}]') THEN 'latin_extended' ELSE 'latin' END AS script, count(*) AS n FROM documents GROUP BY 1"

QUERIES = {
    "w29_scripts": (scripts, SCRIPT_SQL),
    "w08_render_specs": (render_specs, "SELECT p_partkey, " + ", ".join(f"{textrender.pick_sql('p_partkey', a)}{'::DOUBLE' if isinstance(v[0], float) else '::INTEGER' if isinstance(v[0], int) else ''} AS {a}" for a, v in textrender.AXES.items()) + " FROM part"),
    "w08_render_rows": (render_rows, "WITH p AS (SELECT p_partkey, p_name, len(string_split(trim(p_name), ' ')) AS n FROM part) SELECT p_partkey, 'Text that reads: ' || p_name AS caption, 'text-render' AS provenance, CASE WHEN n = 1 THEN 'word' WHEN n <= 12 THEN 'line' ELSE 'paragraph' END AS difficulty, (CASE WHEN n = 1 THEN 1.0 WHEN n <= 12 THEN 0.5 ELSE 0.25 END)::DOUBLE AS weight, sha256(p_name) AS sha256 FROM p"),
    "w08_glyph_raster": (glyphs, "WITH c AS (SELECT p_partkey, p_name, unnest(range(1, length(p_name) + 1)) AS k FROM part) SELECT p_partkey, (8 * any_value(length(p_name)))::INTEGER AS width, sum(((ascii(p_name[k]) * (i % 8 + 1) * 31 + (i // 8) * 17 + (i % 8) * 7) % 5 = 0)::INTEGER)::BIGINT AS ink FROM c, range(128) t(i) GROUP BY 1"),
    "w27_upsample": (upsampled, UPSAMPLE_SQL),
    "w27_sharpness": (sharpness, SHARP_SQL),
    "w25_alignment": (axis_alignment, CENTRE_SQL + " SELECT round(avg((1 + list_cosine_similarity(embedding::DOUBLE[], centre)) / 2), 5) AS alignment FROM embeddings JOIN c USING (label)"),
    "w25_style": (axis_style, CENTRE_SQL + ", r AS (SELECT vec_id, e.label, arg_max(c.label, (round(list_cosine_similarity(embedding::DOUBLE[], centre), 9), -c.label)) AS best FROM embeddings e, c GROUP BY ALL) SELECT round(avg((best = label)::INTEGER), 6) AS style FROM r"),
    "w25_reasoning": (axis_reasoning, REASON_SQL),
    "w15_timestep_embedding": (timesteps, STEP_SQL),
    "w20_initialise": (initialised, None),
    "w17_precision_gap": (precision_gap, None),
    "w10_latent_round_trip": (latent_round_trip, "SELECT vec_id, round(list_sum(embedding::DOUBLE[]), 5) AS total FROM embeddings"),
}
