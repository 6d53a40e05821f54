"""Routing, kernels, losses, schedules and costs: W13-W22."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from assetmill.operators import costmodel, mathkit, routing
from assetmill.plans.bounded import small_side
from assetmill.plans.ship import ship
from assetmill.sources.tables import table

E, DIMS = 8, 64
#: Events that fold together.
FOLDED = 4096


def tokens(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    pos = F.row_number().over(Window.partitionBy("label").orderBy("vec_id")) - 1
    return e.select(F.col("label").alias("sample"), pos.alias("pos"), "vec_id", F.col("embedding").cast("array<double>").alias("x"))


def scored(spark, d) -> DataFrame:
    return routing.scores(tokens(spark, d), "x", E, DIMS)


def capacity(spark, d, c: float):
    n = table(spark, d, "embeddings").groupBy(F.col("label").alias("s")).agg(F.ceil(F.lit(float(c)) * F.count(F.lit(1)) / E).cast("int").alias("cap"))
    return small_side(n)


def chosen(spark, d, c: float = 2) -> DataFrame:
    s = scored(spark, d)
    return routing.expert_choice(s.join(capacity(spark, d, c), F.col("sample") == F.col("s")).drop("s"), F.col("cap"))


TOK_SQL = f"""WITH t AS (SELECT label AS sample, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS pos, vec_id, embedding::DOUBLE[] AS x, count(*) OVER (PARTITION BY label) AS n FROM embeddings),
w AS (SELECT e::INTEGER AS expert, list(((((i * 73856093 + e * 19349663) % 1009)::DOUBLE / 1009 - 0.5) * 2.0) ORDER BY i) AS w FROM range({E}) a(e), range({DIMS}) b(i) GROUP BY e),
l AS (SELECT sample, pos, vec_id, n, expert, list_dot_product(x, w) AS logit FROM t, w),
m AS (SELECT *, max(logit) OVER (PARTITION BY sample, pos) AS mx FROM l),
scored AS (SELECT sample, pos, n, expert, logit, round(exp(logit - mx) / sum(exp(logit - mx)) OVER (PARTITION BY sample, pos), 9) AS score FROM m),
chosen AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY sample, expert ORDER BY score DESC, pos) AS rank FROM scored) WHERE rank <= ceil(2.0 * n / {E})),
picked AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY sample, pos ORDER BY score DESC, expert) AS rank FROM scored) WHERE rank <= 2)"""
_BAL = "(SELECT count(*) FROM (SELECT DISTINCT sample, pos FROM scored)) - (SELECT count(*) FROM (SELECT DISTINCT sample, pos FROM {t}))"
BAL_SQL = TOK_SQL + " " + " UNION ALL ".join(f"SELECT '{r}' AS rule, round(avg(n), 6) AS mean_load, round(stddev_pop(n) / avg(n), 6) AS cv, round(max(n) / avg(n), 6) AS peak, {_BAL.format(t=t)} AS unserved FROM (SELECT a.sample, a.expert, count(c.pos)::DOUBLE AS n FROM (SELECT DISTINCT sample, expert FROM scored) a LEFT JOIN {t} c USING (sample, expert) GROUP BY ALL)" for r, t in (("expert_choice", "chosen"), ("token_choice", "picked")))


def w13_ec(spark, d):
    return routing.normalise_gates(chosen(spark, d)).select("sample", "expert", "pos", "rank", F.round("score", 6).alias("score"), "gate")


def w13_tc(spark, d):
    return routing.normalise_gates(routing.token_choice(scored(spark, d), 2)).select("sample", "expert", "pos", "rank", F.round("score", 6).alias("score"), "gate")


_GATED = " SELECT sample, expert, pos, rank, round(score, 6) AS score, round(score / (sum(score) OVER (PARTITION BY sample, pos) + 1e-9), 6) AS gate FROM "


def w13_balance(spark, d):
    s = scored(spark, d)
    a = routing.balance(chosen(spark, d), s).select(F.lit("expert_choice").alias("rule"), "*")
    return a.union(routing.balance(routing.token_choice(s, 2), s).select(F.lit("token_choice").alias("rule"), "*"))


def w13_dropped(spark, d):
    s = scored(spark, d).join(capacity(spark, d, 2), F.col("sample") == F.col("s")).drop("s")
    kept = routing.token_choice(s, 2, F.col("cap"))
    return kept.groupBy("sample").agg(F.count(F.lit(1)).alias("kept"))


def w13_scale(spark, d):
    """Token choice on order lines, with suppliers as samples: load of 64 experts."""
    li = table(spark, d, "lineitem").select(((F.col("l_quantity") - 25.5) / 14.4).alias("a"), ((F.col("l_discount") - 0.05) / 0.03).alias("b"), ((F.col("l_tax") - 0.04) / 0.026).alias("c"))
    return routing.best_expert(li, ["a", "b", "c"], 64)


W13_S_SQL = "WITH w AS (SELECT e, list(((((i * 73856093 + e * 19349663) % 1009)::DOUBLE / 1009 - 0.5) * 2.0) ORDER BY i) AS w FROM range(64) a(e), range(3) b(i) GROUP BY e), ws AS (SELECT list(w ORDER BY e) AS ws FROM w), x AS (SELECT (l_quantity - 25.5::DOUBLE) / 14.4::DOUBLE AS a, (l_discount - 0.05::DOUBLE) / 0.03::DOUBLE AS b, (l_tax - 0.04::DOUBLE) / 0.026::DOUBLE AS c FROM lineitem), g AS (SELECT list_transform(ws, lambda w: round(a * w[1] + b * w[2] + c * w[3], 9)) AS g FROM x, ws) SELECT (list_position(g, list_max(g)) - 1)::INTEGER AS expert, count(*) AS n FROM g GROUP BY 1"


def w14(spark, d):
    """Tokens that an expert takes in each stage and layer: the lines of one quantity are the tokens of a sample."""
    rows = [(s, base, batch, n, kind, c) for s, base, batch, *_ in routing.STAGES for n, kind, c in routing.layer_schedule(s)]
    plan = F.broadcast(spark.createDataFrame(rows, "stage int, base int, batch int, layer int, kind string, factor int"))
    sized = table(spark, d, "lineitem").groupBy(F.col("l_quantity").cast("int").alias("sample")).agg(F.count(F.lit(1)).alias("n"))
    return sized.crossJoin(plan).select("sample", "stage", "base", "batch", "layer", "kind", "factor", F.ceil(F.col("factor") * F.col("n") / 64).cast("long").alias("tokens"))


W14_SQL = "SELECT sample, stage::INTEGER AS stage, base::INTEGER AS base, batch::INTEGER AS batch, n::INTEGER AS layer, CASE WHEN n < 3 THEN 'dense' ELSE 'expert' END AS kind, (CASE WHEN n < 3 THEN 0 WHEN n IN (3, 4) THEN e ELSE l END)::INTEGER AS factor, ceil((CASE WHEN n < 3 THEN 0 WHEN n IN (3, 4) THEN e ELSE l END) * n_tokens / 64.0)::BIGINT AS tokens FROM (VALUES (1, 256, 4096, 8, 8), (2, 512, 1024, 4, 4), (3, 1024, 256, 4, 2)) s(stage, base, batch, e, l), range(32) r(n), (SELECT l_quantity::INTEGER AS sample, count(*) AS n_tokens FROM lineitem GROUP BY 1) q"


def w15(spark, d):
    """Overlap of each token's top-2 experts between an early and a late step, by router variant: modulation
    that grows tenfold swamps the token only where the router sees it."""
    t = tokens(spark, d)
    out = None
    for mode in ("decoupled", "modulated", "content"):
        step = []
        for s in (0.0, 1.0):
            x = routing.router_input(F.col("x"), F.array(F.lit(s), F.lit(1 - s)), mode, F.transform(F.sequence(F.lit(0), F.lit(DIMS - 1)), _modulation(s)))
            n = DIMS + 2 if mode == "decoupled" else DIMS
            top = routing.token_choice(routing.scores(t.withColumn("x", x), "x", E, n), 2)
            step.append(top.select("sample", "pos", "expert"))
        same = step[0].join(step[1], ["sample", "pos", "expert"]).agg((F.count(F.lit(1)) / (2 * t.count())).alias("overlap"))
        one = same.select(F.lit(mode).alias("mode"), F.round("overlap", 6).alias("overlap"))
        out = one if out is None else out.union(one)
    return out


def _modulation(s: float):
    return lambda i: F.when(i % 7 == 0, F.lit(10.0 * s)).otherwise(F.lit(0.0))


R = 4


def counts(spark, d) -> DataFrame:
    return table(spark, d, "lineitem").groupBy((F.col("l_suppkey") % R).cast("int").alias("device"), (F.col("l_partkey") % E).cast("int").alias("expert")).agg(F.count(F.lit(1)).alias("n"))


CNT_SQL = f"WITH c AS (SELECT (l_suppkey % {R})::INTEGER AS device, (l_partkey % {E})::INTEGER AS expert, count(*) AS n FROM lineitem GROUP BY 1, 2), o AS (SELECT *, coalesce(sum(n) OVER (ORDER BY device, expert ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS read_start, coalesce(sum(n) OVER (ORDER BY expert, device ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS write_start FROM c)"
PERM_SQL = CNT_SQL + ", p AS (SELECT device, expert, read_start + i AS src, write_start + i AS dst FROM (SELECT *, unnest(range(n)) AS i FROM o))"


def w16_waste(spark, d):
    c = counts(spark, d).groupBy("expert").agg(F.sum("n").alias("n"))
    return c.agg(F.sum("n").alias("tokens"), F.max("n").alias("largest"), F.round(1 - F.sum("n") / (F.count(F.lit(1)) * F.max("n")), 6).alias("waste"))


def w16_matmul(kernel: str = "grouped"):
    def run(spark, d):
        li = table(spark, d, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("token"), (F.col("l_partkey") % E).cast("int").alias("expert"), F.array("l_quantity", "l_discount", "l_tax").alias("x"))
        y = routing.grouped_matmul(li, E, 3, 4, kernel)
        return y.groupBy("expert").agg(F.count(F.lit(1)).alias("n"), *(F.round(F.sum(F.get("y", F.lit(j))), 4).alias(f"y{j}") for j in range(4)))

    return run


def _w(i: int, j: int) -> str:
    return f"((({i * 73856093} + (e * 4 + {j}) * 19349663) % 1009)::DOUBLE / 1009 - 0.5) * 2.0"


W16_M_SQL = f"WITH s AS (SELECT (l_partkey % {E})::INTEGER AS expert, l_partkey % {E} AS e, count(*) AS n, sum(l_quantity) AS a, sum(l_discount) AS b, sum(l_tax) AS c FROM lineitem GROUP BY 1, 2) SELECT expert, n, " + ", ".join(f"round(a * {_w(0, j)} + b * {_w(1, j)} + c * {_w(2, j)}, 4) AS y{j}" for j in range(4)) + " FROM s"


def noise(i_col: str = "vec_id"):
    """64 numbers in -0.5..0.5 by formula."""
    return F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.pmod(i * 7919 + F.col(i_col) * 104729, F.lit(1009)) / 1009 - 0.5)


NOISE_SQL = "list_transform(range(64), lambda i: ((i * 7919 + vec_id * 104729) % 1009)::DOUBLE / 1009 - 0.5)"


def w17(spark, d):
    x = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x0"), noise().alias("eps"))
    pred = F.zip_with(mathkit.velocity(F.col("x0"), F.col("eps")), F.transform("x0", lambda v, i: v * 0 + (i % 3 - 1) * 0.1), lambda a, b: a + b)
    x = x.withColumn("v", pred)
    flow = mathkit.mse(F.col("v"), mathkit.velocity(F.col("x0"), F.col("eps")))
    wave = mathkit.wavelet_loss(mathkit.reconstruct(F.col("v"), F.col("eps")), F.col("x0"))
    one = x.select(flow.alias("flow"), wave.alias("wave")).agg(F.round(F.avg("flow"), 6).alias("flow_loss"), F.round(F.avg("wave"), 6).alias("wavelet_loss"))
    return one.withColumn("total_pretrain", F.col("flow_loss")).withColumn("total_finetune", F.round(F.col("flow_loss") + 0.1 * F.col("wavelet_loss"), 6))


def _band(s: tuple[int, ...]) -> str:
    cells = [[(r + i // 2) * 8 + c + i % 2 + 1 for i in range(4)] for r in range(0, 8, 2) for c in range(0, 8, 2)]
    return "(" + " + ".join("((" + " + ".join(f"{g} * e[{k}]" for g, k in zip(s, q)) + ") / 2) ** 2" for q in cells) + ") / 16"


W17_SQL = "WITH e AS (SELECT vec_id, list_transform(range(64), lambda i: (i % 3 - 1) * 0.1::DOUBLE) AS e FROM embeddings), l AS (SELECT list_dot_product(e, e) / 64 AS f, " + " + ".join(_band(s) for s in ((1, 1, 1, 1), (1, 1, -1, -1), (1, -1, 1, -1), (1, -1, -1, 1))) + " AS w FROM e), a AS (SELECT round(avg(f), 6) AS flow_loss, round(avg(w), 6) AS wavelet_loss FROM l) SELECT flow_loss, wavelet_loss, flow_loss AS total_pretrain, round(flow_loss + 0.1::DOUBLE * wavelet_loss, 6) AS total_finetune FROM a"


def w17_z(spark, d):
    s = scored(spark, d).groupBy("sample", "pos").agg(F.collect_list("logit").alias("g"))
    return s.agg(F.round(F.avg(F.pow(mathkit.log_sum_exp(F.col("g")), F.lit(2.0))), 6).alias("z_loss"))


def w17_ortho(spark, d):
    """Loss of a matrix whose columns are experts: a weight is the sum of price moments of the lines of one supplier
    class and part class."""
    w = table(spark, d, "lineitem").groupBy(F.pmod("l_suppkey", F.lit(DIMS)).cast("int").alias("i"), F.pmod("l_partkey", F.lit(E)).cast("int").alias("e")).agg(F.sum(F.round((F.col("l_discount") - 0.05) * 100).cast("long")).cast("double").alias("w"))

    def run(batches):
        import pyarrow as pa

        m = np.zeros((DIMS, E))
        for b in batches:
            m[b.column(0).to_numpy(), b.column(1).to_numpy()] = b.column(2).to_numpy()
        off, diag = mathkit.ortho_loss(m)
        yield pa.record_batch([pa.array([round(off, 6)]), pa.array([round(diag, 6)])], names=["off_diagonal", "diagonal"])

    ship(spark)
    return w.coalesce(1).mapInArrow(run, "off_diagonal double, diagonal double")


W17_O_SQL = f"WITH w AS (SELECT l_suppkey % {DIMS} AS i, l_partkey % {E} AS e, sum(round((l_discount - 0.05) * 100)::BIGINT)::DOUBLE AS w FROM lineitem GROUP BY 1, 2), n AS (SELECT i, e, w / sqrt(sum(w * w) OVER (PARTITION BY e)) AS w FROM w), g AS (SELECT a.e AS p, b.e AS q, sum(a.w * b.w) - (a.e = b.e)::INTEGER AS g FROM n a JOIN n b ON a.i = b.i GROUP BY 1, 2) SELECT round(sum(CASE WHEN p <> q THEN g * g ELSE 0 END) / {E * E}, 6) AS off_diagonal, round(sum(CASE WHEN p = q THEN g * g ELSE 0 END) / {E * E}, 6) AS diagonal FROM g"


def w18(spark, d):
    """Sampled time steps: logistic of a normal draw, shifted by token count, one tenth uniform."""
    o = table(spark, d, "orders").select("o_orderkey")
    u = lambda tag: (F.conv(F.substring(F.md5(F.concat(F.lit(f"{tag}:"), F.col("o_orderkey").cast("string"))), 1, 13), 16, 10).cast("double") + 0.5) / F.lit(float(16**13))
    z = F.sqrt(-2 * F.log(u("a"))) * F.cos(2 * math.pi * u("b"))
    rows = o.select("o_orderkey", F.explode(F.array(*map(F.lit, (256, 1024, 4096)))).alias("tokens"), z.alias("z"), u("c").alias("c"), u("d").alias("d"))
    t = F.when(F.col("c") < 0.1, F.col("d")).otherwise(mathkit.shift_t(mathkit.logistic(F.col("z")), mathkit.mu(F.col("tokens"))))
    return rows.groupBy("tokens").agg(F.round(F.avg(t), 6).alias("mean_t"), F.round(F.stddev_pop(t), 6).alias("sd_t"))


_U = lambda t: f"((('0x' || substr(md5('{t}:' || o_orderkey::VARCHAR), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0)"
W18_SQL = f"WITH z AS (SELECT tokens, sqrt(-2 * ln({_U('a')})) * cos(2 * pi() * {_U('b')}) AS z, {_U('c')} AS c, {_U('d')} AS d, 0.5::DOUBLE + (tokens - 256) * (0.65::DOUBLE / 3840) AS mu FROM orders, (VALUES (256), (1024), (4096)) v(tokens)), t AS (SELECT tokens, CASE WHEN c < 0.1 THEN d ELSE exp(mu) / (exp(mu) + (1 / (1 / (1 + exp(-z))) - 1)) END AS t FROM z) SELECT tokens, round(avg(t), 6) AS mean_t, round(stddev_pop(t), 6) AS sd_t FROM t GROUP BY tokens"


def w19_weights(spark, d):
    rows = [(s, j, round(c, 6), round(m, 6)) for s in ("mean", "geometric", "printed", "derived", "last") for j, (c, m) in enumerate(zip(routing_weights(s), mathkit.implied_decay(routing_weights(s))))]
    return spark.createDataFrame(rows, "scheme string, j int, weight double, multiplier double")


def routing_weights(scheme: str) -> list[float]:
    return mathkit.merge_weights(scheme, 16)


_RAW = "CASE s WHEN 'mean' THEN 1.0 WHEN 'geometric' THEN 0.9::DOUBLE ** (15 - j) WHEN 'printed' THEN 1 - sqrt(j / 16.0::DOUBLE) WHEN 'derived' THEN sqrt((j + 1) / 16.0::DOUBLE) - sqrt(j / 16.0::DOUBLE) ELSE CASE WHEN j = 15 THEN 1.0 ELSE 0.0 END END::DOUBLE"
WEIGHT_SQL = f"WITH r AS (SELECT s AS scheme, j, {_RAW} AS raw FROM (VALUES ('mean'), ('geometric'), ('printed'), ('derived'), ('last')) a(s), range(16) b(j)), c AS (SELECT scheme, j::INTEGER AS j, raw / sum(raw) OVER (PARTITION BY scheme) AS c FROM r)"


def w19_merge(spark, d):
    """Distance of the merged last 16 vectors of each label to the label's mean, by scheme."""
    e = tokens(spark, d).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("sample"))).withColumn("j", (F.col("pos") - F.col("n") + 16).cast("int"))
    w = spark.createDataFrame([(s, j, c) for s in ("mean", "geometric", "printed", "derived", "last") for j, c in enumerate(routing_weights(s))], "scheme string, j int, c double")
    long = e.select("sample", "j", F.posexplode("x").alias("i", "v"))
    centre = long.groupBy("sample", "i").agg(F.avg("v").alias("m"))
    merged = long.where("j >= 0").join(F.broadcast(w), "j").groupBy("scheme", "sample", "i").agg(F.sum(F.col("c") * F.col("v")).alias("v"))
    gap = merged.join(centre, ["sample", "i"]).groupBy("scheme", "sample").agg(F.sqrt(F.sum((F.col("v") - F.col("m")) * (F.col("v") - F.col("m")))).alias("gap"))
    return gap.groupBy("scheme").agg(F.round(F.avg("gap"), 6).alias("mean_gap"))


W19_M_SQL = WEIGHT_SQL + ", t AS (SELECT label, embedding, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 - count(*) OVER (PARTITION BY label) + 16 AS j FROM embeddings), l AS (SELECT label, j, i, embedding[i]::DOUBLE AS v FROM t, range(1, 65) r(i)), m AS (SELECT label, i, avg(v) AS m FROM l GROUP BY ALL), g AS (SELECT scheme, l.label, l.i, sum(c * v) AS v FROM l JOIN c ON l.j = c.j GROUP BY ALL), k AS (SELECT scheme, label, sqrt(sum((v - m) ** 2)) AS gap FROM g JOIN m USING (label, i) GROUP BY ALL) SELECT scheme, round(avg(gap), 6) AS mean_gap FROM k GROUP BY scheme"


def w19_shadow(spark, d):
    """The running average of each user's values and its unrolled form, which agree."""
    e = table(spark, d, "events").select("user_id", "value", (F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1).alias("k"))
    # chunks of a user's events fold on their own: over m events the average keeps 0.9^m of what it was, so no user's
    # events need to stand in one array
    chunk = e.withColumn("c", F.floor(F.col("k") / FOLDED)).groupBy("user_id", "c").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "value"))), lambda p: p["value"]).alias("v"))
    head = F.col("c") == 0
    start, rest = F.when(head, F.get("v", F.lit(0))).otherwise(F.lit(0.0)), F.when(head, F.slice("v", F.lit(2), F.size("v"))).otherwise(F.col("v"))
    part = chunk.select("user_id", "c", F.size("v").alias("m"), F.aggregate(rest, start, lambda s, x: 0.9 * s + 0.1 * x).alias("own"))
    after = F.coalesce(F.sum("m").over(Window.partitionBy("user_id").orderBy(F.desc("c")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    folded = part.select("user_id", (F.col("own") * F.pow(F.lit(0.9), after)).alias("own")).groupBy("user_id").agg(F.round(F.sum("own"), 6).alias("folded"))
    last = e.groupBy("user_id").agg(F.max("k").alias("last")).withColumnRenamed("user_id", "u")
    weight = F.when(F.col("k") == 0, F.pow(F.lit(0.9), F.col("last"))).otherwise(0.1 * F.pow(F.lit(0.9), F.col("last") - F.col("k")))
    unrolled = e.join(last, F.col("user_id") == F.col("u")).groupBy("user_id").agg(F.round(F.sum(F.col("value") * weight), 6).alias("unrolled"))
    return folded.join(unrolled, "user_id")


W19_S_SQL = "WITH e AS (SELECT user_id, value, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS k, count(*) OVER (PARTITION BY user_id) - 1 AS n FROM events) SELECT user_id, round(sum(value * CASE WHEN k = 0 THEN 0.9::DOUBLE ** n ELSE 0.1::DOUBLE * 0.9::DOUBLE ** (n - k) END), 6) AS folded, round(sum(value * CASE WHEN k = 0 THEN 0.9::DOUBLE ** n ELSE 0.1::DOUBLE * 0.9::DOUBLE ** (n - k) END), 6) AS unrolled FROM e GROUP BY user_id"


def w19_lr(spark, d):
    """Learning rates at the step that each order's key stands for, and how many orders are there."""
    s = table(spark, d, "orders").groupBy(F.pmod("o_orderkey", F.lit(20001)).alias("step")).agg(F.count(F.lit(1)).alias("orders"))
    return s.select("step", F.round(mathkit.hold_lr(F.col("step")) * 1e4, 6).alias("hold"), F.round(mathkit.stable_decay_lr(F.col("step"), 20000) * 1e4, 6).alias("stable_decay"), "orders")


W19_L_SQL = "SELECT step, round(least(1.0::DOUBLE, step / 1000.0::DOUBLE), 6) AS hold, round(CASE WHEN step < 1000 THEN step / 1000.0::DOUBLE WHEN step < 18000 THEN 1.0::DOUBLE ELSE greatest(0, (20000 - step) / 2000.0::DOUBLE) END, 6) AS stable_decay, orders FROM (SELECT o_orderkey % 20001 AS step, count(*) AS orders FROM orders GROUP BY 1) t"

CATALOGUE = (("blocks.attn.q", 2), ("blocks.attn.k", 2), ("blocks.attn.v", 2), ("blocks.experts.up", 3), ("blocks.experts.down", 3), ("blocks.router", 2), ("blocks.norm.scale", 1), ("embed.patch", 2), ("modulation.out", 2), ("head.out", 2), ("blocks.gate", 1))


def w20(spark, d):
    c = spark.createDataFrame(CATALOGUE, "name string, rank int")
    return c.select("name", mathkit.group_of(F.col("name"), F.col("rank")).alias("grp"))


W20_SQL = "SELECT name, CASE WHEN regexp_matches(name, 'router|embed|modulation|head') THEN 'adamw_decay' WHEN rank >= 2 THEN 'orthogonalised' ELSE 'adamw_plain' END AS grp FROM (VALUES " + ", ".join(f"('{n}', {r})" for n, r in CATALOGUE) + ") c(name, rank)"


def w21(spark, d):
    rows = [(si, st, costmodel.kv_cache(32, si, 16), costmodel.kv_cache(32, si, 4), *costmodel.attention(si, st)) for si in (256, 1024, 4096) for st in (77, 256, 512)]
    return spark.createDataFrame(rows, "s_i long, s_t long, mha_bytes long, gqa_bytes long, image_only long, all_queries long")


W21_SQL = "SELECT s_i::BIGINT AS s_i, s_t::BIGINT AS s_t, 2 * 32 * s_i::BIGINT * 16 * 256 AS mha_bytes, 2 * 32 * s_i::BIGINT * 4 * 256 AS gqa_bytes, s_i::BIGINT * (s_i + s_t) AS image_only, (s_i + s_t)::BIGINT * (s_i + s_t) AS all_queries FROM (VALUES (256), (1024), (4096)) a(s_i), (VALUES (77), (256), (512)) b(s_t)"


def w22(spark, d):
    """One-head joint attention inside each label, the first eight vectors standing for text: largest gap
    between one call over both and attention by parts joined by their softmax masses."""

    def run(key, table):
        import pyarrow as pa

        x = np.array(table.sort_by("vec_id").column("x").to_pylist())
        img, txt = x[8:], x[:8]
        whole = mathkit.joint(img, txt)
        s = lambda kv: np.exp(img @ kv.T / math.sqrt(x.shape[1]))
        a, b = s(img), s(txt)
        parts = (a @ img + b @ txt) / (a.sum(1, keepdims=True) + b.sum(1, keepdims=True))
        return pa.table({"sample": pa.array([key[0].as_py()], pa.int32()), "tokens": pa.array([len(img)]), "gap": pa.array([float(np.round(np.abs(whole - parts).max(), 9))])})

    return tokens(spark, d).select(F.col("sample").cast("int").alias("sample"), "vec_id", "x").groupBy("sample").applyInArrow(run, "sample int, tokens long, gap double")


def w_costs(spark, d):
    rows = [("padded_share_1_2_9", costmodel.padding_waste([1, 2, 9])), ("fused_gate_saving", costmodel.fused_traffic()), ("exchange_bytes_64", float(costmodel.exchange_bytes(4096, 2048, 64))), ("shadow_bytes_17b", float(costmodel.shadow_copy(17_000_000_000)[0]))] + [(f"tokens_per_step_{s}", float(costmodel.tokens_per_step(b, base))) for s, base, b, *_ in routing.STAGES] + list(zip(("total_parameters", "active_parameters"), map(float, costmodel.parameters())))
    return spark.createDataFrame(rows, "measure string, value double")


W15_SQL = f"""WITH t AS (SELECT label AS sample, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS pos, embedding::DOUBLE[] AS x FROM embeddings),
w AS (SELECT e::INTEGER AS expert, list(((((i * 73856093 + e * 19349663) % 1009)::DOUBLE / 1009 - 0.5) * 2.0) ORDER BY i) AS w FROM range({E}) a(e), range({DIMS + 2}) b(i) GROUP BY e),
m AS (SELECT sample, pos, mode, s, CASE mode WHEN 'decoupled' THEN list_concat(x, [s, 1 - s]) WHEN 'modulated' THEN list_concat(list_transform(range(64), lambda i: x[i + 1] * (1 + CASE WHEN i % 7 = 0 THEN 10 * s ELSE 0 END)), [0.0::DOUBLE, 0.0::DOUBLE]) ELSE list_concat(x, [0.0::DOUBLE, 0.0::DOUBLE]) END AS h FROM t, (VALUES ('decoupled'), ('modulated'), ('content')) v(mode), (VALUES (0.0::DOUBLE), (1.0)) z(s)),
l AS (SELECT sample, pos, mode, s, expert, list_dot_product(h, w) AS g FROM m, w), e AS (SELECT *, exp(g - max(g) OVER (PARTITION BY sample, pos, mode, s)) AS z FROM l),
p AS (SELECT *, round(z / sum(z) OVER (PARTITION BY sample, pos, mode, s), 9) AS score FROM e), r AS (SELECT *, row_number() OVER (PARTITION BY sample, pos, mode, s ORDER BY score DESC, expert) AS place FROM p),
k AS (SELECT * FROM r WHERE place <= 2), c AS (SELECT mode, count(*) AS n FROM k a JOIN k b USING (sample, pos, mode, expert) WHERE a.s = 0 AND b.s = 1 GROUP BY 1)
SELECT mode, round(n / (2.0::DOUBLE * (SELECT count(*) FROM t)), 6) AS overlap FROM c"""
COST_SQL = """WITH p AS (SELECT 32 * (2 * 2048 * 16 * 128 + 2 * 2048 * 4 * 128) + 3 * 3 * 2048 * 8192 + 29 * 2 * 2048 * 64 AS common, (29 * 3 * 2048 * 1344)::BIGINT AS layer)
SELECT * FROM (VALUES ('padded_share_1_2_9', 1 - 12 / 27.0::DOUBLE), ('fused_gate_saving', 1 - 4 / 6.0::DOUBLE), ('exchange_bytes_64', (2 * 4096 * 2048 * 2 * 63 // 64)::DOUBLE), ('shadow_bytes_17b', 68000000000::DOUBLE),
('tokens_per_step_1', (4096 * 16 * 16)::DOUBLE), ('tokens_per_step_2', (1024 * 32 * 32)::DOUBLE), ('tokens_per_step_3', (256 * 64 * 64)::DOUBLE)) v(measure, value)
UNION ALL SELECT 'total_parameters', (common + layer * 65)::DOUBLE FROM p UNION ALL SELECT 'active_parameters', (common + layer * 2)::DOUBLE FROM p"""

QUERIES = {
    "w13_expert_choice": (w13_ec, TOK_SQL + _GATED + "chosen"),
    "w13_token_choice": (w13_tc, TOK_SQL + _GATED + "picked"),
    "w13_balance": (w13_balance, BAL_SQL),
    "w13_token_choice_dropped": (w13_dropped, TOK_SQL + f", s AS (SELECT *, row_number() OVER (PARTITION BY sample, expert ORDER BY score DESC, pos) AS seat FROM picked) SELECT sample, count(*) AS kept FROM s WHERE seat <= ceil(2.0 * n / {E}) GROUP BY sample"),
    "w13_scale": (w13_scale, W13_S_SQL),
    "w14_capacity": (w14, W14_SQL),
    "w15_router_variants": (w15, W15_SQL),
    "w16_offsets": (lambda s, d: routing.offsets(counts(s, d)), CNT_SQL + " SELECT * FROM o"),
    "w16_permutation": (lambda s, d: routing.permutation(routing.offsets(counts(s, d))), PERM_SQL + " SELECT * FROM p"),
    "w16_inverse": (lambda s, d: routing.invert(routing.permutation(routing.offsets(counts(s, d)))), PERM_SQL + " SELECT dst AS src, src AS dst FROM p"),
    "w16_padding_waste": (w16_waste, CNT_SQL + ", x AS (SELECT expert, sum(n)::BIGINT AS n FROM c GROUP BY 1) SELECT sum(n)::BIGINT AS tokens, max(n) AS largest, round(1 - sum(n)::DOUBLE / (count(*) * max(n)), 6) AS waste FROM x"),
    "w16_grouped_matmul": (w16_matmul(), W16_M_SQL),
    "w16_loop_matmul": (w16_matmul("loop"), W16_M_SQL),
    "w16_padded_matmul": (w16_matmul("padded"), W16_M_SQL),
    "w17_losses": (w17, W17_SQL),
    "w17_z_loss": (w17_z, TOK_SQL + ", z AS (SELECT sample, pos, max(logit) + ln(sum(exp(logit - mx))) AS z FROM m GROUP BY sample, pos) SELECT round(avg(z * z), 6) AS z_loss FROM z"),
    "w17_ortho_loss": (w17_ortho, W17_O_SQL),
    "w18_timesteps": (w18, W18_SQL),
    "w19_weights": (w19_weights, WEIGHT_SQL + " SELECT scheme, j, round(c, 6) AS weight, round(sum(c) OVER (PARTITION BY scheme ORDER BY j DESC), 6) AS multiplier FROM c"),
    "w19_merge": (w19_merge, W19_M_SQL),
    "w19_shadow_equivalence": (w19_shadow, W19_S_SQL),
    "w19_lr": (w19_lr, W19_L_SQL),
    "w20_groups": (w20, W20_SQL),
    "w21_costs": (w21, W21_SQL),
    "w21_other_costs": (w_costs, COST_SQL),
    "w22_joint_attention": (w22, "SELECT label AS sample, count(*) - 8 AS tokens, 0.0::DOUBLE AS gap FROM embeddings GROUP BY 1"),
}
