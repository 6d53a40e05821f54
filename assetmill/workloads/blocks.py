"""Blocks, exchange, capacity, merging and sweeps beside their baselines: W13-W24 beyond the headline queries."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from assetmill.operators import allocation, costmodel, mathkit, routing
from assetmill.plans.ship import ship
from assetmill.sources.tables import table
from assetmill.workloads.evaluation import CHECKS_SQL, checks
from assetmill.workloads.network import DIMS, TOK_SQL, E, R, chosen, counts, noise, tokens

VEC_SQL = "WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x, list_transform(range(64), lambda i: ((i * 7919 + vec_id * 104729) % 1009)::DOUBLE / 1009 - 0.5) AS r FROM embeddings)"
_RAMP = "list_transform(range(64), lambda i: (i % 5 + 1)::DOUBLE)"


def vectors(s, d):
    return table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"), noise().alias("r"))


def _ramp(c):
    """One number of a vector: its products with 1 to 5, repeating."""
    return F.round(F.aggregate(F.transform(c, lambda v, i: v * (i % 5 + 1)), F.lit(0.0), lambda t, v: t + v), 5)


def norms(s, d):
    x = F.col("x")
    return vectors(s, d).select("vec_id", _ramp(mathkit.rms_norm(x)).alias("rms"), _ramp(mathkit.layer_norm(x)).alias("layer"), _ramp(mathkit.progressive_norm(x, 4)).alias("progressive"), _ramp(mathkit.norm_scale(x, F.lit(0.25))).alias("scaled"))


_RMS = "list_transform({x}, lambda a: a / sqrt(list_dot_product({x}, {x}) / 64 + 1e-6))"
_LAYER = "list_transform({x}, lambda a: (a - list_sum({x}) / 64) / sqrt(list_dot_product({x}, {x}) / 64 - (list_sum({x}) / 64) ** 2 + 1e-6))"
NORM_SQL = VEC_SQL + f", n AS (SELECT vec_id, {_RMS.format(x='x')} AS a, {_LAYER.format(x='x')} AS b FROM v) SELECT vec_id, round(list_dot_product(a, {_RAMP}), 5) AS rms, round(list_dot_product(b, {_RAMP}), 5) AS layer, round(list_dot_product(a, {_RAMP}) / 2, 5) AS progressive, round(list_dot_product(b, {_RAMP}) * 1.25::DOUBLE, 5) AS scaled FROM n"


def fused_chain(s, d):
    """Gate, residual, norm and scale as one expression and as four columns."""
    gate, scale = F.lit(0.3), F.lit(0.25)
    one = vectors(s, d).withColumn("fused", mathkit.norm_scale(mathkit.gated_residual(F.col("x"), F.col("r"), gate), scale))
    steps = one.withColumn("_gated", F.transform("r", lambda v: F.tanh(gate) * v)).withColumn("_sum", F.zip_with("x", "_gated", lambda a, b: a + b)).withColumn("_norm", mathkit.layer_norm(F.col("_sum"))).withColumn("steps", F.transform("_norm", lambda v: v * (1 + scale)))
    gap = F.array_max(F.zip_with("fused", "steps", lambda a, b: F.abs(a - b)))
    return steps.select("vec_id", _ramp(F.col("fused")).alias("fused"), F.round(gap, 9).alias("gap"))


FUSED_SQL = VEC_SQL + f", y AS (SELECT vec_id, list_transform(list_zip(x, r), lambda p: p[1] + tanh(0.3::DOUBLE) * p[2]) AS y FROM v), n AS (SELECT vec_id, {_LAYER.format(x='y')} AS b FROM y) SELECT vec_id, round(list_dot_product(b, {_RAMP}) * 1.25::DOUBLE, 5) AS fused, 0.0::DOUBLE AS gap FROM n"


def qk_norm(s, d):
    """Attention logits of a vector and a fixed one, before and after both are normalised."""
    plain, normed = mathkit.dot(F.col("x"), F.col("r")), mathkit.dot(mathkit.rms_norm(F.col("x")), mathkit.rms_norm(F.col("r")))
    return vectors(s, d).select("vec_id", F.round(plain / 8, 6).alias("plain"), F.round(normed / 8, 6).alias("normed"))


QK_SQL = VEC_SQL + f" SELECT vec_id, round(list_dot_product(x, r) / 8, 6) AS plain, round(list_dot_product({_RMS.format(x='x')}, {_RMS.format(x='r')}) / 8, 6) AS normed FROM v"


def grouped_heads(s, d):
    """Each vector as eight tokens of eight numbers: four query heads on two shared key heads, against the same heads
    written out, and against four key heads of their own."""
    ship(s)

    def run(batches):
        import pyarrow as pa

        w = np.array([[[routing.weight(i, h * 8 + j, 5) for j in range(8)] for i in range(8)] for h in range(12)])
        for b in batches:
            ids, xs = b.column(0).to_pylist(), b.column(1).to_pylist()
            out = []
            for i, x in zip(ids, xs):
                t = np.array(x).reshape(8, 8)
                q, k, v = t @ w[:4], t @ w[4:8], t @ w[8:12]
                shared = mathkit.gqa(q, k[:2], v[:2])
                written = mathkit.gqa(q, np.repeat(k[:2], 2, axis=0), np.repeat(v[:2], 2, axis=0))
                own = mathkit.gqa(q, k, v)
                out.append((i, float(np.abs(shared - written).max()), float(np.abs(shared - own).max())))
            if out:
                yield pa.record_batch([pa.array(c) for c in zip(*out)], names=["vec_id", "shared", "own"])

    e = vectors(s, d).select("vec_id", "x").mapInArrow(run, "vec_id long, shared double, own double")
    return e.agg(F.count(F.lit(1)).alias("n"), F.round(F.max("shared"), 9).alias("gap_written_out"), (F.min("own") > 0).alias("own_heads_differ"))


def text_kv(s, d):
    """Keys of a prompt computed once and joined to fifty steps, and computed at every step: projections and largest gap."""
    key = lambda x: F.transform(x, lambda v: v * 1.5 - 0.25)
    prompts = table(s, d, "embeddings").where("vec_id % 10 = 0").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    steps = s.range(50).withColumnRenamed("id", "step")
    cached = prompts.select("vec_id", "x", key(F.col("x")).alias("kept")).join(F.broadcast(steps))
    both = cached.withColumn("again", key(F.col("x")))
    gap = F.array_max(F.zip_with("kept", "again", lambda a, b: F.abs(a - b)))
    return both.agg(F.count_distinct("vec_id").alias("cached_projections"), F.count(F.lit(1)).alias("step_projections"), F.max(gap).alias("gap"))


def scope(s, d):
    """Token passes through experts of one image at each size, with text tokens kept out and let in."""
    rows = [(si, st, si * 29, (si + st) * 29, round(1 - si / (si + st), 6)) for si in (256, 1024, 4096) for st in (77, 256, 512)]
    return s.createDataFrame(rows, "s_i long, s_t long, image_only long, with_text long, saved double")


def patches(s, d):
    """The 8 x 8 grid as sixteen patches of 2 x 2: their sums."""
    x = F.col("x")
    cut = F.array(*(sum((F.get(x, F.lit((r + i) * 8 + c + j)) for i in (0, 1) for j in (0, 1)), F.lit(0.0)) for r in range(0, 8, 2) for c in range(0, 8, 2)))
    return vectors(s, d).select("vec_id", F.posexplode(cut).alias("patch", "total")).select("vec_id", F.col("patch").cast("long").alias("patch"), F.round("total", 5).alias("total"))


def token_counts(s, d):
    """Image tokens of each crop size, 16 x 16 a token, and the lines whose quantity is its width in steps of 64."""
    from assetmill.operators import curriculum

    lines = table(s, d, "lineitem").groupBy((F.col("l_quantity").cast("int") * 64).alias("side")).agg(F.count(F.lit(1)).alias("lines"))
    c = s.createDataFrame([(b, w, h, (w // 16) * (h // 16)) for b in (256, 512, 1024) for w, h in curriculum.crops(b)], "base int, w int, h int, tokens int")
    return c.join(lines, F.col("w") == F.col("side"), "left").select("base", "w", "h", "tokens", F.coalesce("lines", F.lit(0)).alias("lines"))


TOKENS_SQL = "SELECT b.base::INTEGER AS base, (w * 64)::INTEGER AS w, (h * 64)::INTEGER AS h, (w * h * 16)::INTEGER AS tokens, coalesce(n, 0) AS lines FROM (VALUES (256), (512), (1024)) b(base), range(1, 257) x(w), range(1, 257) y(h) LEFT JOIN (SELECT l_quantity::INTEGER AS q, count(*) AS n FROM lineitem GROUP BY 1) l ON l.q = w WHERE w * h * 4096 <= base * base AND w * h * 4096 >= 0.5 * base * base AND greatest(w, h) <= 4 * least(w, h)"


def combined(s, d):
    """Shared expert on every token plus gated outputs of the experts that took it; untaken tokens keep the shared one.
    Expert e scales by 1 + e/10, the shared one by a half."""
    gate = routing.normalise_gates(chosen(s, d)).groupBy("sample", "pos").agg(F.sum(F.col("gate") * (1 + F.col("expert") / 10)).alias("routed"), F.count(F.lit(1)).alias("experts"))
    t = tokens(s, d).join(gate, ["sample", "pos"], "left")
    y = F.transform("x", lambda v: v * (0.5 + F.coalesce("routed", F.lit(0.0))))
    return t.select("sample", "pos", _ramp(y).alias("y"), F.coalesce("experts", F.lit(0)).alias("experts"))


COMBINE_SQL = TOK_SQL + f", g AS (SELECT sample, pos, expert, round(score / (sum(score) OVER (PARTITION BY sample, pos) + 1e-9), 6) AS gate FROM chosen), r AS (SELECT sample, pos, sum(gate * (1 + expert / 10.0::DOUBLE)) AS routed, count(*) AS experts FROM g GROUP BY 1, 2) SELECT sample, pos, round(list_dot_product(x, {_RAMP}) * (0.5::DOUBLE + coalesce(routed, 0)), 5) AS y, coalesce(experts, 0) AS experts FROM t LEFT JOIN r USING (sample, pos)"


def _modes(s, d, steps: int):
    """For each token and router variant: how often its best expert changes over the steps, how far its scores move
    when only the modulation does, and how far an expert's output does."""
    ship(s)

    def run(batches):
        import pyarrow as pa

        w = np.array([[routing.weight(i, e, 3) for e in range(E)] for i in range(DIMS + 2)])
        at = np.linspace(0, 1, steps)
        scale = np.where(np.arange(DIMS) % 7 == 0, 10.0, 0.0)
        soft = lambda z: mathkit.softmax(z)
        for b in batches:
            out = []
            for i, x in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                x = np.array(x)
                mod = x * (1 + at[:, None] * scale)
                inputs = {"decoupled": np.concatenate([np.repeat(x[None], steps, 0), at[:, None], 1 - at[:, None]], axis=1), "modulated": mod, "content": np.repeat(x[None], steps, 0)}
                for mode, h in inputs.items():
                    p = soft(h @ w[: h.shape[1]])
                    still = h.copy()
                    if mode == "modulated":
                        still[-1] = mod[0]
                    moved = float(np.abs(soft(h[-1:] @ w[: h.shape[1]]) - soft(still[-1:] @ w[: h.shape[1]])).max())
                    top = p.argmax(axis=1)
                    out.append((i, mode, len(set(top.tolist())), moved, float(np.abs(mod[-1] - mod[0]).max())))
            if out:
                yield pa.record_batch([pa.array(c) for c in zip(*out)], names=["vec_id", "mode", "tops", "score_moves", "output_moves"])

    return vectors(s, d).select("vec_id", "x").mapInArrow(run, "vec_id long, mode string, tops long, score_moves double, output_moves double")


def collapse(s, d):
    """Share of tokens whose best expert never changes over fifty steps, and the mean number of best experts."""
    return _modes(s, d, 50).groupBy("mode").agg(F.round(F.avg((F.col("tops") == 1).cast("int")), 6).alias("steady"), F.round(F.avg("tops"), 6).alias("experts"))


def separation(s, d):
    """What the modulation alone moves: scores only where the router sees it, the expert's output always."""
    return _modes(s, d, 2).groupBy("mode").agg((F.max("score_moves") > 1e-9).alias("score_moves"), (F.max("output_moves") > 1e-9).alias("output_moves"))


def capacity_compare(s, d):
    """Tokens that experts process for one sample, by stage: capacity by depth, one factor for all layers, and no
    dense layers in front. The lines of one quantity are the tokens of a sample."""
    rows = []
    for stage, _, _, early, _ in routing.STAGES:
        by_depth = sum(f for _, kind, f in routing.layer_schedule(stage) if kind == "expert")
        rows.append((stage, by_depth, early * 29, early * 32, round(1 - by_depth / (early * 29), 6)))
    plan = F.broadcast(s.createDataFrame(rows, "stage int, by_depth long, uniform long, no_dense_prefix long, saved double"))
    sized = table(s, d, "lineitem").groupBy(F.col("l_quantity").cast("int").alias("sample")).agg(F.count(F.lit(1)).alias("n"))
    return sized.crossJoin(plan).select("sample", "stage", *((F.col("n") * F.col(c)).alias(c) for c in ("by_depth", "uniform", "no_dense_prefix")), "saved")


def _weights(layer: int, rows: int, cols: int) -> np.ndarray:
    return np.array([[routing.weight(i, j, layer) for j in range(cols)] for i in range(rows)])


def swiglu(s, d):
    """Gated experts of three products on order lines, fused and not; three numbers in, two hidden, one out."""
    ship(s)

    def run(batches):
        import pyarrow as pa

        w1, w3, w2 = ([_weights(100 * k + e, *shape) for e in range(E)] for k, shape in ((1, (3, 2)), (2, (3, 2)), (3, (2, 1))))
        for b in batches:
            if b.num_rows:
                expert = b.column(0).to_numpy()
                x = np.stack([c.to_numpy() for c in b.columns[1:]], axis=1)
                y, gap = np.zeros(len(x)), 0.0
                for e in range(E):
                    here = expert == e
                    y[here] = routing.swiglu(x[here], w1[e], w3[e], w2[e])[:, 0]
                    if here.any():
                        gap = max(gap, float(np.abs(y[here] - routing.swiglu(x[here], w1[e], w3[e], w2[e], fused=False)[:, 0]).max()))
                yield pa.record_batch([b.column(0), pa.array(y), pa.array(np.full(len(y), gap))], names=["expert", "y", "gap"])

    li = table(s, d, "lineitem").select((F.col("l_partkey") % E).cast("int").alias("expert"), (F.col("l_quantity") / 50).alias("a"), F.col("l_discount").alias("b"), F.col("l_tax").alias("c"))
    return li.mapInArrow(run, "expert int, y double, gap double").groupBy("expert").agg(F.round(F.sum("y"), 4).alias("y"), F.round(F.max("gap"), 9).alias("gap"))


def _w(layer: str, i: int, j: int) -> str:
    return f"((({i * 73856093 + j * 19349663} + ({layer}) * 83492791) % 1009)::DOUBLE / 1009 - 0.5) * 2.0"


_G = lambda k, j: "(a * ({}) + b * ({}) + c * ({}))".format(*(_w(f"{100 * k} + e", i, j) for i in range(3)))
SWIGLU_SQL = f"WITH x AS (SELECT l_partkey % {E} AS e, l_quantity / 50 AS a, l_discount AS b, l_tax AS c FROM lineitem), g AS (SELECT e, {_G(1, 0)} AS g0, {_G(1, 1)} AS g1, {_G(2, 0)} AS u0, {_G(2, 1)} AS u1 FROM x) SELECT e::INTEGER AS expert, round(sum(g0 / (1 + exp(-g0)) * u0 * ({_w('300 + e', 0, 0)}) + g1 / (1 + exp(-g1)) * u1 * ({_w('300 + e', 1, 0)})), 4) AS y, 0.0::DOUBLE AS gap FROM g GROUP BY e"


def exchange(s, d):
    """Tokens go to the device of their expert and back: how many go from each device to each, and what comes back.
    Counts are exchanged first; both moves are repartitions by device, and results are the ones made in place."""
    li = table(s, d, "lineitem").select((F.col("l_suppkey") % R).alias("token"), (F.col("l_partkey") % E).cast("int").alias("expert"), F.array("l_quantity", "l_discount", "l_tax").alias("x"), F.pmod(F.xxhash64("l_orderkey", "l_linenumber"), F.lit(64)).alias("part"))
    there = li.repartition(F.col("expert") % R, "part")  # a device is many tasks, so a popular expert is too
    y = routing.grouped_matmul(there, E, 3, 1)
    back = y.repartition("token", F.pmod(F.xxhash64("y"), F.lit(64)))  # a token carries the device it came from
    return back.groupBy(F.col("token").cast("int").alias("home"), (F.col("expert") % R).alias("device")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.get("y", F.lit(0))), 4).alias("y"))


EXCHANGE_SQL = f"WITH x AS (SELECT l_suppkey % {R} AS home, l_partkey % {E} AS e, l_quantity AS a, l_discount AS b, l_tax AS c FROM lineitem) SELECT home::INTEGER AS home, (e % {R})::INTEGER AS device, count(*) AS n, round(sum(" + " + ".join(f"{k} * (((({i * 73856093} + e * 19349663) % 1009)::DOUBLE / 1009 - 0.5) * 2.0)" for i, k in enumerate("abc")) + "), 4) AS y FROM x GROUP BY 1, 2"


def host_permutation(s, d):
    """Baseline: counts of devices and experts, at most R x E rows, go to the driver, which lays out the permutation;
    tokens that it places elsewhere than the distributed one."""
    got = {(r.device, r.expert): r.n for r in counts(s, d).collect()}
    read, write, at = {}, {}, 0
    for k in sorted(got):
        read[k], at = at, at + got[k]
    at = 0
    for k in sorted(got, key=lambda k: k[::-1]):
        write[k], at = at, at + got[k]
    starts = s.createDataFrame([(*k, got[k], read[k], write[k]) for k in got], "device int, expert int, n long, read_start long, write_start long")
    own, host = routing.permutation(routing.offsets(counts(s, d))), routing.permutation(starts)
    same = own.join(host, ["src", "dst"], "left_semi")
    return own.agg(F.count(F.lit(1)).alias("tokens")).join(same.agg(F.count(F.lit(1)).alias("alike")))


def single_expert(s, d):
    """One expert a device: the grouped product of that expert alone against a plain product."""
    li = table(s, d, "lineitem").where(F.col("l_partkey") % E == 3).select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("token"), F.lit(3).alias("expert"), F.array("l_quantity", "l_discount", "l_tax").alias("x"))
    y = routing.grouped_matmul(li, E, 3, 1).agg(F.count(F.lit(1)).alias("n"), F.sum(F.get("y", F.lit(0))).alias("grouped"))
    plain = li.agg(F.sum(sum((F.get("x", F.lit(i)) * routing.weight(i, 3) for i in range(3)), F.lit(0.0))).alias("plain"))
    return y.join(plain).select("n", F.round("grouped", 4).alias("grouped"), F.round("plain", 4).alias("plain"))


def placement(s, d):
    """Where each part's expert is placed, and how many lines go there."""
    where = F.broadcast(s.createDataFrame(routing.placement(64, 64, 8), "expert int, device int, node int"))
    sent = table(s, d, "lineitem").groupBy(F.pmod("l_partkey", F.lit(64)).cast("int").alias("expert")).agg(F.count(F.lit(1)).alias("lines"))
    return where.join(sent, "expert", "left").select("expert", "device", "node", F.coalesce("lines", F.lit(0)).alias("lines"))


def split_optimizer(s, d):
    """Orthogonalised steps of three matrices side by side and as one: smallest and largest singular value of each
    part of the step. Taken as one, a large part takes the room of the small ones."""
    rng = np.random.default_rng(3)
    parts = {n: rng.normal(size=(24, 8)) * scale for n, scale in (("q", 1.0), ("k", 0.1), ("v", 0.01))}
    whole = mathkit.newton_schulz(np.concatenate(list(parts.values()), axis=1), 40)
    rows = []
    for i, (name, g) in enumerate(parts.items()):
        for kind, step in (("split", mathkit.newton_schulz(g, 40)), ("fused", whole[:, 8 * i : 8 * i + 8])):
            sv = np.linalg.svd(step, compute_uv=False)
            rows.append((name, kind, round(float(sv[-1]), 4), round(float(sv[0]), 4)))
    return s.createDataFrame(rows, "part string, kind string, smallest double, largest double")


def momentum_steps(s, d):
    """Root mean square of one orthogonalised step, over the base rate, by shape: the scale makes it 0.2 for all."""
    rng, rows = np.random.default_rng(4), []
    for shape in ((16, 16), (16, 64), (64, 16), (8, 128)):
        g = rng.normal(size=shape)
        w, _ = mathkit.ortho_momentum_step(np.zeros(shape), g, np.zeros(shape), lr=1.0, decay=0.0)
        rows.append((f"{shape[0]}x{shape[1]}", round(float(np.sqrt((w**2).mean())), 3), round(mathkit.rms_scale(shape), 6)))
    return s.createDataFrame(rows, "shape string, step_rms double, scale double")


def sparse_merge(s, d):
    """Weight that the newest k of checkpoints kept every 2,500 steps leave to all before them, at a decay of
    0.9999 a step: small once k is well over 1 / (2,500 x 0.0001) = 4. A line's quantity is its k."""
    at = table(s, d, "lineitem").groupBy(F.col("l_quantity").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("lines"))
    return at.select("k", F.round(F.pow(F.lit(0.9999), F.col("k") * 2500), 9).alias("left_out"), "lines")


def remerge(s, d):
    """Mean of the last 16 vectors of each label before and after eight more come: distance between the two."""
    n = F.count(F.lit(1)).over(Window.partitionBy("sample"))
    t = tokens(s, d).withColumn("back", n - 1 - F.col("pos")).where("back < 24")
    long = t.select("sample", "back", F.posexplode("x").alias("i", "v")).groupBy("sample", "i").agg(F.avg(F.when(F.col("back") < 16, F.col("v"))).alias("after"), F.avg(F.when(F.col("back") >= 8, F.col("v"))).alias("before"))
    return long.groupBy("sample").agg(F.round(F.sqrt(F.sum(F.pow(F.col("after") - F.col("before"), F.lit(2.0)))), 6).alias("moved"))


REMERGE_SQL = "WITH t AS (SELECT label AS sample, embedding, count(*) OVER (PARTITION BY label) - row_number() OVER (PARTITION BY label ORDER BY vec_id) AS back FROM embeddings), l AS (SELECT sample, i, avg(CASE WHEN back < 16 THEN embedding[i]::DOUBLE END) AS a, avg(CASE WHEN back >= 8 THEN embedding[i]::DOUBLE END) AS b FROM t, range(1, 65) r(i) WHERE back < 24 GROUP BY ALL) SELECT sample, round(sqrt(sum((a - b) ** 2)), 6) AS moved FROM l GROUP BY 1"


def forward_unchanged(s, d):
    """Experts that tokens pick before and after one step of the orthogonal term on the router, and beside a z-loss,
    which only reads the logits: picks that change, of all."""
    ship(s)

    def run(batches):
        import pyarrow as pa

        w = np.array([[routing.weight(i, e) for e in range(E)] for i in range(DIMS)])
        stepped = mathkit.ortho_step(w)
        for b in batches:
            if b.num_rows:
                x = np.array(b.column(0).to_pylist())
                logit = x @ w
                top = np.argsort(-logit, axis=1, kind="stable")[:, :2]
                z = np.log(np.exp(logit).sum(axis=1)) ** 2
                again = np.argsort(-logit, axis=1, kind="stable")[:, :2]
                after = np.argsort(-(x @ stepped), axis=1, kind="stable")[:, :2]
                yield pa.record_batch([pa.array((top != again).any(axis=1)), pa.array((top != after).any(axis=1)), pa.array(z)], names=["by_z", "by_step", "z"])

    e = vectors(s, d).select("x").mapInArrow(run, "by_z boolean, by_step boolean, z double")
    return e.agg(F.count(F.lit(1)).alias("tokens"), F.count_if("by_z").alias("changed_by_z"), F.count_if("by_step").alias("changed_by_step"))


def uniform_share(s, d):
    """Mean step time and its share below a tenth with none, a tenth and all of the draws uniform, and unshifted."""
    o = table(s, d, "orders").select("o_orderkey")
    u = lambda tag: (F.conv(F.substring(F.md5(F.concat(F.lit(f"{tag}:"), F.col("o_orderkey").cast("string"))), 1, 13), 16, 10).cast("double") + 0.5) / F.lit(float(16**13))
    z = F.sqrt(-2 * F.log(u("a"))) * F.cos(2 * math.pi * u("b"))
    rows = o.select(z.alias("z"), u("c").alias("c"), u("d").alias("d"), F.explode(F.array(F.lit(0.0), F.lit(0.1), F.lit(1.0))).alias("share"), F.lit(1).alias("one"))
    plain = mathkit.logistic(F.col("z"))
    shifted = mathkit.shift_t(plain, mathkit.mu(F.lit(1024)))
    t = lambda base: F.when(F.col("c") < F.col("share"), F.col("d")).otherwise(base)
    return rows.groupBy("share").agg(F.round(F.avg(t(shifted)), 6).alias("shifted"), F.round(F.avg(t(plain)), 6).alias("unshifted"), F.round(F.avg((t(shifted) < 0.1).cast("int")), 6).alias("early"))


_U = lambda t: f"((('0x' || substr(md5('{t}:' || o_orderkey::VARCHAR), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0)"
SHARE_SQL = f"WITH z AS (SELECT share, 1 / (1 + exp(-(sqrt(-2 * ln({_U('a')})) * cos(2 * pi() * {_U('b')})))) AS p, {_U('c')} AS c, {_U('d')} AS d, exp(0.5::DOUBLE + 768 * (0.65::DOUBLE / 3840)) AS m FROM orders, (VALUES (0.0::DOUBLE), (0.1), (1.0)) v(share)), t AS (SELECT share, CASE WHEN c < share THEN d ELSE m / (m + (1 / p - 1)) END AS s, CASE WHEN c < share THEN d ELSE p END AS u FROM z) SELECT share, round(avg(s), 6) AS shifted, round(avg(u), 6) AS unshifted, round(avg((s < 0.1)::INTEGER), 6) AS early FROM t GROUP BY 1"


def interpolated(s, d):
    """A quarter of the way from data to noise, the velocity there, and the data that both give back."""
    x, r, t = F.col("x"), F.col("r"), 0.25
    z = mathkit.interpolate(x, r, F.lit(t))
    v = mathkit.velocity(x, r)
    back = F.zip_with(z, v, lambda a, b: a + t * b)
    gap = F.array_max(F.zip_with(back, x, lambda a, b: F.abs(a - b)))
    return vectors(s, d).select("vec_id", _ramp(z).alias("z"), _ramp(v).alias("v"), F.round(gap, 9).alias("gap"))


def overlaid(s, d):
    """A heat grid blended over the picture it belongs to."""
    return vectors(s, d).select("vec_id", _ramp(allocation.overlay(F.col("x"), F.col("r"), 0.4)).alias("blend"))


def merge_gain(s, d):
    """Points that one scorer has over another by category and in all: checks at two thresholds stand for merged and
    unmerged weights."""
    c = checks(s, d).select("prompt", "ordinal", "category", "passed")
    li = table(s, d, "lineitem")
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
    base = li.select(F.col("l_orderkey").alias("prompt"), F.row_number().over(order).alias("ordinal"), (F.col("l_discount") <= 0.04).cast("int").alias("plain"))
    both = c.join(base, ["prompt", "ordinal"])
    return both.rollup("category").agg(F.round(100 * F.avg("passed"), 6).alias("merged"), F.round(100 * F.avg("plain"), 6).alias("unmerged"), F.round(100 * (F.avg("passed") - F.avg("plain")), 6).alias("gain"))


def sweep(s, d):
    """Pass rates over two settings and all their margins."""
    li = table(s, d, "lineitem").select((F.col("l_linenumber") % 3).cast("int").alias("guidance"), (F.col("l_orderkey") % 2).cast("int").alias("steps"), (F.col("l_discount") <= 0.05).cast("int").alias("merged"), (F.col("l_discount") <= 0.04).cast("int").alias("unmerged"))
    return li.cube("guidance", "steps").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("merged"), 6).alias("merged"), F.round(F.avg("unmerged"), 6).alias("unmerged"))


def text_costs(s, d):
    """Text projections of an image with and without the cache, by steps."""
    return s.createDataFrame([(n, *costmodel.text_work(n)) for n in (1, 10, 25, 50)], "steps int, cached int, recomputed int")


_ONE = " + ".join(f"{k} * (((({i * 73856093} + 3 * 19349663) % 1009)::DOUBLE / 1009 - 0.5) * 2.0)" for i, k in enumerate(("l_quantity", "l_discount", "l_tax")))

QUERIES = {
    "w10_patches": (patches, VEC_SQL + " SELECT vec_id, r.p AS patch, round(" + " + ".join(f"x[(p // 4 * 2 + {i}) * 8 + p % 4 * 2 + {j} + 1]" for i in (0, 1) for j in (0, 1)) + ", 5) AS total FROM v, range(16) r(p)"),
    "w10_token_counts": (token_counts, TOKENS_SQL),
    "w13_norms": (norms, NORM_SQL),
    "w13_fused_chain": (fused_chain, FUSED_SQL),
    "w13_combined": (combined, COMBINE_SQL),
    "w14_capacity_compare": (capacity_compare, "SELECT sample, stage::INTEGER AS stage, (n * (2 * e + 27 * l))::BIGINT AS by_depth, (n * 29 * e)::BIGINT AS uniform, (n * 32 * e)::BIGINT AS no_dense_prefix, round(1 - (2 * e + 27 * l)::DOUBLE / (29 * e), 6) AS saved FROM (VALUES (1, 8, 8), (2, 4, 4), (3, 4, 2)) v(stage, e, l), (SELECT l_quantity::INTEGER AS sample, count(*) AS n FROM lineitem GROUP BY 1) l"),
    "w15_collapse": (collapse, None),
    "w15_separation": (separation, "SELECT * FROM (VALUES ('decoupled', false, true), ('modulated', true, true), ('content', false, true)) v(mode, score_moves, output_moves)"),
    "w16_swiglu": (swiglu, SWIGLU_SQL),
    "w16_exchange": (exchange, EXCHANGE_SQL),
    "w16_host_permutation": (host_permutation, "SELECT count(*) AS tokens, count(*) AS alike FROM lineitem"),
    "w16_single_expert": (single_expert, f"SELECT n, y AS grouped, y AS plain FROM (SELECT count(*) AS n, round(sum({_ONE}), 4) AS y FROM lineitem WHERE l_partkey % {E} = 3)"),
    "w16_placement": (placement, "SELECT e::INTEGER AS expert, e::INTEGER AS device, (e // 8)::INTEGER AS node, coalesce(n, 0) AS lines FROM range(64) t(e) LEFT JOIN (SELECT l_partkey % 64 AS p, count(*) AS n FROM lineitem GROUP BY 1) l ON p = e"),
    "w17_forward_unchanged": (forward_unchanged, "SELECT count(*) AS tokens, 0::BIGINT AS changed_by_z, 0::BIGINT AS changed_by_step FROM embeddings"),
    "w18_interpolate": (interpolated, VEC_SQL + f" SELECT vec_id, round(0.75::DOUBLE * list_dot_product(x, {_RAMP}) + 0.25::DOUBLE * list_dot_product(r, {_RAMP}), 5) AS z, round(list_dot_product(x, {_RAMP}) - list_dot_product(r, {_RAMP}), 5) AS v, 0.0::DOUBLE AS gap FROM v"),
    "w27_overlay": (overlaid, VEC_SQL + f" SELECT vec_id, round(0.6::DOUBLE * list_dot_product(x, {_RAMP}) + 0.4::DOUBLE * list_dot_product(r, {_RAMP}), 5) AS blend FROM v"),
    "w18_uniform_share": (uniform_share, SHARE_SQL),
    "w19_sparse_merge": (sparse_merge, "SELECT k::INTEGER AS k, round(pow(0.9999::DOUBLE, k * 2500), 9) AS left_out, lines FROM (SELECT l_quantity::INTEGER AS k, count(*) AS lines FROM lineitem GROUP BY 1) t"),
    "w19_remerge": (remerge, REMERGE_SQL),
    "w20_split_optimizer": (split_optimizer, None),
    "w20_momentum_steps": (momentum_steps, None),
    "w21_text_work": (text_costs, "SELECT n::INTEGER AS steps, 1 AS cached, n::INTEGER AS recomputed FROM (VALUES (1), (10), (25), (50)) v(n)"),
    "w21_scope": (scope, "SELECT i::BIGINT AS s_i, t::BIGINT AS s_t, (i * 29)::BIGINT AS image_only, ((i + t) * 29)::BIGINT AS with_text, round(1 - i::DOUBLE / (i + t), 6) AS saved FROM (VALUES (256), (1024), (4096)) a(i), (VALUES (77), (256), (512)) b(t)"),
    "w22_qk_norm": (qk_norm, QK_SQL),
    "w22_grouped_heads": (grouped_heads, "SELECT count(*) AS n, 0.0::DOUBLE AS gap_written_out, true AS own_heads_differ FROM embeddings"),
    "w22_text_kv": (text_kv, "SELECT count(*) AS cached_projections, 50 * count(*) AS step_projections, 0.0::DOUBLE AS gap FROM embeddings WHERE vec_id % 10 = 0"),
    "w23_merge_gain": (merge_gain, CHECKS_SQL.replace("AS passed,", "AS passed, (l_discount <= 0.04)::INTEGER AS plain,", 1) + " SELECT category, round(100 * avg(passed), 6) AS merged, round(100 * avg(plain), 6) AS unmerged, round(100 * (avg(passed) - avg(plain)), 6) AS gain FROM c GROUP BY ROLLUP (category)"),
    "w23_sweep": (sweep, "SELECT (l_linenumber % 3)::INTEGER AS guidance, (l_orderkey % 2)::INTEGER AS steps, count(*) AS n, round(avg((l_discount <= 0.05)::INTEGER), 6) AS merged, round(avg((l_discount <= 0.04)::INTEGER), 6) AS unmerged FROM lineitem GROUP BY CUBE ((l_linenumber % 3)::INTEGER, (l_orderkey % 2)::INTEGER)"),
}
