"""Expert routing: scores, selection rules, gates, balance, capacities, permutations."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from assetmill.plans.ship import ship


def weight(i: int, e: int, layer: int = 0, scale: float = 2.0) -> float:
    """Router weights from integer hashing, the same in every engine."""
    return (((i * 73856093 + e * 19349663 + layer * 83492791) % 1009) / 1009 - 0.5) * scale


def router_input(x: Column, t: Column, mode: str = "decoupled", modulation: Column | None = None) -> Column:
    """decoupled: token and time side by side; modulated: the scaled token; content: the token alone."""
    if mode == "decoupled":
        return F.concat(x, t)
    if mode == "modulated":
        return F.zip_with(x, modulation, lambda a, s: a * (1 + s))
    return x


def scores(df: DataFrame, x: str, experts: int, dims: int, layer: int = 0) -> DataFrame:
    """One row per token and expert: logit and softmax score, built inside the row from a literal matrix."""
    table = F.array(*(F.array(*(F.lit(weight(i, e, layer)) for i in range(dims))) for e in range(experts)))
    dot = lambda w: F.aggregate(F.zip_with(F.col(x), w, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    with_logits = df.withColumn("_l", F.transform(table, dot))
    top = F.array_max("_l")
    z = F.aggregate(F.transform("_l", lambda v: F.exp(v - top)), F.lit(0.0), lambda s, v: s + v)
    return with_logits.withColumn("_m", top).withColumn("_z", z).select(*df.columns, F.posexplode("_l").alias("expert", "logit"), "_m", "_z").withColumn("score", F.round(F.exp(F.col("logit") - F.col("_m")) / F.col("_z"), 9)).drop("_m", "_z")


def expert_choice(scored: DataFrame, capacity: Column, within: tuple[str, ...] = ("sample",)) -> DataFrame:
    """Every expert of a sample takes its ``capacity`` best tokens, ties to the lower token; ``within`` names
    what else selects apart."""
    w = Window.partitionBy(*within, "expert").orderBy(F.desc("score"), "pos")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= capacity)


def token_choice(scored: DataFrame, k: int, capacity: Column | None = None) -> DataFrame:
    """Every token takes its ``k`` best experts; with a capacity an expert drops what is over it."""
    w = Window.partitionBy("sample", "pos").orderBy(F.desc("score"), "expert")
    out = scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    if capacity is not None:
        e = Window.partitionBy("sample", "expert").orderBy(F.desc("score"), "pos")
        out = out.withColumn("seat", F.row_number().over(e)).where(F.col("seat") <= capacity).drop("seat")
    return out


def normalise_gates(chosen: DataFrame, alpha: float = 1.0, eps: float = 1e-9) -> DataFrame:
    w = Window.partitionBy("sample", "pos")
    return chosen.withColumn("gate", F.round(alpha * F.col("score") / (F.sum("score").over(w) + eps), 6))


def balance(chosen: DataFrame, scored: DataFrame) -> DataFrame:
    """Load measures over (sample, expert): mean, coefficient of variation, largest over mean; and tokens no
    expert took."""
    all_ = scored.select("sample", "expert").distinct()
    load = all_.join(chosen.groupBy("sample", "expert").agg(F.count(F.lit(1)).alias("n")), ["sample", "expert"], "left").select(F.coalesce("n", F.lit(0)).alias("n"))
    served = chosen.select("sample", "pos").distinct().withColumn("served", F.lit(1))
    tokens = scored.select("sample", "pos").distinct().join(served, ["sample", "pos"], "left").agg(F.count_if(F.col("served").isNull()).alias("unserved"))
    one = load.agg(F.round(F.avg("n"), 6).alias("mean_load"), F.round(F.stddev_pop("n") / F.avg("n"), 6).alias("cv"), F.round(F.max("n") / F.avg("n"), 6).alias("peak"))
    return one.crossJoin(tokens).select("mean_load", "cv", "peak", "unserved")


def capacity(c: float, s: int, e: int) -> int:
    return math.ceil(c * s / e)


#: Stage: base resolution, batch, capacity factors (first expert layers, the others).
STAGES = ((1, 256, 4096, 8, 8), (2, 512, 1024, 4, 4), (3, 1024, 256, 4, 2))
LAYERS, FIRST_EXPERT_LAYER, EARLY = 32, 3, (3, 4)


def layer_schedule(stage: int = 3) -> list[tuple[int, str, int]]:
    """Layer, kind and capacity factor."""
    _, _, _, early, late = STAGES[stage - 1]
    return [(n, "dense", 0) if n < FIRST_EXPERT_LAYER else (n, "expert", early if n in EARLY else late) for n in range(LAYERS)]


# --- permutation and grouped products ---------------------------------------------------------------


def offsets(counts: DataFrame) -> DataFrame:
    """From rows (device, expert, n): read_start in device order, write_start in expert order."""
    read = Window.orderBy("device", "expert").rowsBetween(Window.unboundedPreceding, -1)
    write = Window.orderBy("expert", "device").rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn("read_start", F.coalesce(F.sum("n").over(read), F.lit(0))).withColumn("write_start", F.coalesce(F.sum("n").over(write), F.lit(0)))


def permutation(starts: DataFrame) -> DataFrame:
    """Source and target index of every token."""
    span = F.when(F.col("n") > 0, F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).otherwise(F.array().cast("array<long>"))
    return starts.select("device", "expert", "read_start", "write_start", F.explode(span).alias("i")).select("device", "expert", (F.col("read_start") + F.col("i")).alias("src"), (F.col("write_start") + F.col("i")).alias("dst"))


def invert(perm: DataFrame) -> DataFrame:
    return perm.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def expert_weights(experts: int, dims: int, out_dims: int) -> np.ndarray:
    """Matrices of all experts, by formula."""
    return np.array([[[weight(i, e * out_dims + j) for j in range(out_dims)] for i in range(dims)] for e in range(experts)])


def _by_expert(x: np.ndarray, expert: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Rows put side by side by expert in one buffer, one product a group, and back in their order."""
    order = np.argsort(expert, kind="stable")
    at = np.searchsorted(expert[order], np.arange(len(w) + 1))
    buf, out = x[order], np.empty((len(x), w.shape[2]))
    for e, (a, b) in enumerate(zip(at, at[1:])):
        out[order[a:b]] = buf[a:b] @ w[e]
    return out


def _padded(x: np.ndarray, expert: np.ndarray, w: np.ndarray) -> np.ndarray:
    groups = [np.flatnonzero(expert == e) for e in range(len(w))]
    out = np.empty((len(x), w.shape[2]))
    for index, y in zip(groups, padded_matmul([x[g] for g in groups], w)):
        out[index] = y
    return out


def _one_by_one(x: np.ndarray, expert: np.ndarray, w: np.ndarray) -> np.ndarray:
    out = np.empty((len(x), w.shape[2]))
    for e in range(len(w)):
        here = expert == e
        out[here] = x[here] @ w[e]
    return out


KERNELS = {"grouped": _by_expert, "padded": _padded, "loop": _one_by_one}


def grouped_matmul(tokens: DataFrame, experts: int, dims: int, out_dims: int, kernel: str = "grouped") -> DataFrame:
    """Rows (token, expert, x): y = x W_e. Weights come from a formula, so tokens are grouped by expert inside
    each Arrow batch and no expert's tokens meet in one task. ``kernel``: grouped, padded or loop."""
    ship(tokens.sparkSession)
    product = KERNELS[kernel]

    def run(batches):
        import pyarrow as pa

        w = expert_weights(experts, dims, out_dims)
        for b in batches:
            if b.num_rows:
                x = np.array(b.column("x").to_pylist(), dtype=np.float64)
                y = product(x, b.column("expert").to_numpy(), w)
                yield pa.record_batch([b.column("token"), b.column("expert"), pa.array(list(y), pa.list_(pa.float64()))], names=["token", "expert", "y"])

    return tokens.select("token", "expert", "x").mapInArrow(run, "token long, expert int, y array<double>")


def best_expert(df: DataFrame, features: list[str], experts: int) -> DataFrame:
    """How many rows have each expert as their best, the first of equals; counted inside each batch before
    anything is shuffled. Null features count as zero."""
    ship(df.sparkSession)

    def run(batches):
        import pyarrow as pa

        w = np.array([[weight(i, e) for e in range(experts)] for i in range(len(features))])
        for b in batches:
            if b.num_rows:
                x = np.stack([np.nan_to_num(c.to_numpy(zero_copy_only=False)) for c in b.columns], axis=1)
                n = np.bincount(np.round(x @ w, 9).argmax(axis=1), minlength=experts)
                hit = np.flatnonzero(n)
                yield pa.record_batch([pa.array(hit.astype(np.int32)), pa.array(n[hit])], names=["expert", "n"])

    return df.select(*(F.col(f).cast("double") for f in features)).mapInArrow(run, "expert int, n long").groupBy("expert").agg(F.sum("n").alias("n"))


def padded_matmul(x: list[np.ndarray], w: np.ndarray) -> list[np.ndarray]:
    """Baseline: pad all groups to the largest and multiply as one batch."""
    most = max((len(g) for g in x), default=0)
    stack = np.stack([np.pad(g, ((0, most - len(g)), (0, 0))) for g in x])
    return [y[: len(g)] for g, y in zip(x, stack @ w)]


def loop_matmul(x: list[np.ndarray], w: np.ndarray) -> list[np.ndarray]:
    """Baseline: one product an expert."""
    return [g @ m for g, m in zip(x, w)]


def ragged_matmul(x: list[np.ndarray], w: np.ndarray) -> list[np.ndarray]:
    """All groups in one buffer with offsets."""
    at = np.cumsum([0, *map(len, x)])
    buf, out = np.concatenate(x), np.empty((at[-1], w.shape[2]))
    for e in range(len(x)):
        np.matmul(buf[at[e] : at[e + 1]], w[e], out=out[at[e] : at[e + 1]])
    return [out[a:b] for a, b in zip(at, at[1:])]


def swiglu(x: np.ndarray, w1: np.ndarray, w3: np.ndarray, w2: np.ndarray, fused: bool = True) -> np.ndarray:
    """Gated expert of three products; unfused keeps the gate and the product as arrays of their own."""
    g, u = x @ w1, x @ w3
    if fused:
        g /= 1 + np.exp(-g)
        g *= u
        return g @ w2
    gate = g / (1 + np.exp(-g))
    return (gate * u) @ w2


def combine(shared: np.ndarray, routed: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> np.ndarray:
    """Shared output plus gate-weighted outputs (token index, gate, value); untaken tokens keep the shared one."""
    out = shared.copy()
    for index, gate, value in routed:
        np.add.at(out, index, gate[:, None] * value)
    return out


def placement(devices: int, experts: int, nodes: int) -> list[tuple[int, int, int]]:
    """expert, device and node when experts are dealt over devices."""
    return [(e, e % devices, (e % devices) * nodes // devices) for e in range(experts)]
