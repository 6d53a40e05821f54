"""Near duplicates among embeddings by cosine, compared tile by tile along principal axes.

Vectors are compared within a label. They are scaled to length one and turned onto the principal axes
of all vectors, the widest first. Rows of a label are cut into tiles along the first axis; tiles that
lie too far apart on it cannot hold a pair over the threshold and are not compared. In a pair of tiles
the products of the leading axes are summed first; what the remaining axes can add is at most the
product of the two remaining lengths, and a pair is given up as soon as the sum and that bound stay
below the threshold. The few pairs left are decided by the cosine of the vectors as given, in double
precision. Equal vectors are one node with a count, so groups of copies do not make pairs.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from assetmill.operators.components import components, spread
from assetmill.plans.bounded import small_side
from assetmill.plans.scratch import Scratch
from assetmill.plans.ship import ship

LEAST = 0.98
#: Rows of a tile where a label is small, bins of the first axis, axes added at a time, and slack for rounding in the bound.
TILE, BINS, STEP, SLACK = 1024, 200, 8, 1e-9
#: Times that a tile grows with the largest label, so that fewer pairs of tiles hold a row, and rows for which it does so once.
MOST_GROWTH, GROWTH_ROWS = 16, 65_536
#: Numbers that the principal axes of all lengths may hold; rarer lengths are compared on their own axes, which
#: the bound holds on as well.
AXIS_NUMBERS = 4_000_000


def principal_axes(classes: DataFrame, numbers: int = AXIS_NUMBERS) -> dict[int, np.ndarray]:
    """For each length of the vectors (columns dims, v) their axes as columns, by falling second moment. Executors
    add up the moments, the driver gets dims x dims numbers a length, the most frequent lengths first, up to
    ``numbers`` in all."""
    most = int(numbers**0.5)
    lengths = classes.where(F.col("dims") <= most).groupBy("dims").count().orderBy(F.desc("count"), "dims").limit(most).collect()
    chosen, left = [], numbers
    for dims, _ in lengths:
        if dims * dims <= left:
            chosen.append(dims)
            left -= dims * dims
    if not chosen:
        return {}

    def run(batches):
        import pyarrow as pa

        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            dims = batch.column(0).to_numpy()
            for d in np.unique(dims).tolist():
                x = np.array(batch.column(1).filter(pa.array(dims == d)).to_pylist(), dtype=np.float64)
                x /= np.linalg.norm(x, axis=1, keepdims=True)
                sums[d] = sums.get(d, 0) + x.T @ x
        for d, m in sums.items():
            i, j = np.meshgrid(np.arange(d), np.arange(d), indexing="ij")
            yield pa.record_batch([pa.array(np.full(d * d, d, dtype=np.int32)), pa.array(i.ravel().astype(np.int32)), pa.array(j.ravel().astype(np.int32)), pa.array(m.ravel())], names=["dims", "i", "j", "s"])

    got = classes.where(F.col("dims").isin(chosen)).select("dims", "v").mapInArrow(run, "dims int, i int, j int, s double").groupBy("dims", "i", "j").agg(F.sum("s").alias("s")).toPandas()
    out = {}
    for d, rows in got.groupby("dims"):
        moments = np.zeros((d, d))
        moments[rows["i"], rows["j"]] = rows["s"]
        out[int(d)] = np.linalg.eigh(moments)[1][:, ::-1].copy()
    return out


def _turn(x: np.ndarray, axes: dict[int, np.ndarray]) -> np.ndarray:
    """Unit vectors of the rows of x on the axes of their length, or as they are."""
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    return x @ axes[x.shape[1]] if x.shape[1] in axes else x


def _linked(a: np.ndarray, b: np.ndarray, ta: np.ndarray, tb: np.ndarray, least: float, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs with cosine ``least`` or more between the rows of a and b (``same``: each pair once);
    ta and tb are their unit vectors on the axes."""
    dims = ta.shape[1]
    rest_a = np.sqrt(np.maximum(0, np.cumsum((ta**2)[:, ::-1], axis=1)[:, ::-1]))
    rest_b = np.sqrt(np.maximum(0, np.cumsum((tb**2)[:, ::-1], axis=1)[:, ::-1]))
    k = min(STEP, dims)
    part = ta[:, :k] @ tb[:, :k].T
    if k < dims:
        alive = part + np.outer(rest_a[:, k], rest_b[:, k]) >= least - SLACK
    else:
        alive = part >= least - SLACK
    if same:
        alive = np.triu(alive, 1)
    i, j = np.nonzero(alive)
    part = part[i, j]
    while k < dims and len(i):
        more = min(dims, k + STEP)
        part = part + np.einsum("ij,ij->i", ta[i, k:more], tb[j, k:more])
        k = more
        keep = part + (rest_a[i, k] * rest_b[j, k] if k < dims else 0.0) >= least - SLACK
        i, j, part = i[keep], j[keep], part[keep]
    if len(i):
        dot = np.einsum("ij,ij->i", a[i], b[j])
        keep = dot / (np.linalg.norm(a, axis=1)[i] * np.linalg.norm(b, axis=1)[j]) >= least
        i, j = i[keep], j[keep]
    return i, j


def _roots(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The least index that each of n nodes reaches."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[i], root[j])
        new = root.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _pairs(v: np.ndarray, t: np.ndarray, left: np.ndarray, right: np.ndarray | None, least: float) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of a task, strip by strip; without ``right``, inside ``left``."""
    out = [(np.zeros(0, dtype=np.int64),) * 2]
    for a in range(0, len(left), TILE):
        one = left[a : a + TILE]
        if right is None:
            i, j = _linked(v[one], v[one], t[one], t[one], least, True)
            out.append((one[i], one[j]))
        other = right if right is not None else left[a + TILE :]
        for b in range(0, len(other), TILE):
            two = other[b : b + TILE]
            i, j = _linked(v[one], v[two], t[one], t[two], least, False)
            out.append((one[i], two[j]))
    return np.concatenate([x for x, _ in out]), np.concatenate([x for _, x in out])


def near_vectors(rows: DataFrame, scratch: Scratch, least: float = LEAST, tile: int | None = None) -> DataFrame:
    """One row per vector: vec_id, n_links (other rows linked directly), component_id (smallest vec_id
    that links reach, itself included), kept (vec_id = component_id).

    ``rows`` has vec_id, embedding and label. Null labels, null or zero vectors and vectors with a null
    or non-finite part link with nothing, as do vectors of different lengths. Vectors whose squared length
    over- or underflows are scaled by their largest part first. Equal rows link with each
    other; null ids name no component while there are others; an empty table gives no rows.
    """
    ship(rows.sparkSession)
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    norm = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    own = rows.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"))
    fit = F.col("label").isNotNull() & F.col("v").isNotNull() & (F.size("v") > 0) & finite
    own = own.withColumn("v", F.when(fit, F.col("v"))).withColumn("_top", F.array_max(F.transform("v", F.abs))).withColumn("_norm", norm)
    usual = F.col("_norm").between(1e-280, 1e280)
    own = own.withColumn("v", F.when(usual, F.col("v")).when(F.col("_top") > 0, F.transform("v", lambda x: x / F.col("_top")))).drop("_top", "_norm")
    key = F.when(F.col("v").isNotNull(), F.md5(F.to_json(F.struct("label", "v"))))
    own = scratch.keep(own.withColumn("key", key), "rows")
    classes = scratch.keep(own.where("key IS NOT NULL").groupBy("key").agg(F.min("vec_id").alias("first"), F.count(F.lit(1)).alias("n"), F.first("label").alias("label"), F.first("v").alias("v")).withColumn("dims", F.size("v")), "classes")
    found = scratch.keep(_links(classes, scratch, least, tile), "found")
    degree = found.where("b IS NULL").groupBy("a").agg(F.sum("w").alias("near"))
    reach = components(found.where("b IS NOT NULL").select("a", "b"), scratch)
    named = classes.select("key", "first", "n").join(reach, F.col("key") == F.col("node"), "left").join(degree, F.col("key") == F.col("a"), "left").select("key", "first", (F.col("n") - 1 + F.coalesce("near", F.lit(0))).alias("n_links"), F.coalesce("component", "key").alias("root"))
    known = scratch.keep(spread(scratch.keep(named, "named"), "root", F.min("first"), "component_id").select(F.col("key").alias("k"), "n_links", "component_id"), "known")
    scratch.drop("classes", "lead", "bins", "sides", "found", "named")
    out = own.select("vec_id", "key").join(known, F.col("key") == F.col("k"), "left")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").cast("long").alias("component_id")).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def _links(classes: DataFrame, scratch: Scratch, least: float, tile: int | None) -> DataFrame:
    """Rows (a, null, w): w rows link to class a; and rows (a, b, 0): a reaches b."""
    axes = principal_axes(classes)
    turned = classes.sparkSession.sparkContext.broadcast(axes)
    if tile is None:
        most = classes.groupBy("label", "dims").count().agg(F.max("count")).first()[0] or 0
        tile = TILE * min(MOST_GROWTH, 1 + most // GROWTH_ROWS)

    def first_axis(batches):
        import pyarrow as pa

        for batch in batches:
            dims, lead = batch.column(4).to_numpy(), np.zeros(batch.num_rows)
            for d in np.unique(dims).tolist():
                x = np.array(batch.column(3).filter(pa.array(dims == d)).to_pylist(), dtype=np.float64)
                lead[dims == d] = _turn(x, turned.value)[:, 0]
            yield pa.record_batch([*batch.columns, pa.array(lead)], names=[*batch.schema.names, "lead"])

    group = ["label", "dims"]
    lead = classes.select(F.col("label").cast("string").alias("label"), "key", "n", "v", "dims").select("key", "label", "n", "v", "dims").mapInArrow(first_axis, "key string, label string, n long, v array<double>, dims int, lead double")
    lead = scratch.keep(lead.withColumn("bin", F.least(F.lit(BINS - 1), F.greatest(F.lit(0), F.floor((F.col("lead") + 1) * (BINS / 2)).cast("int")))), "lead")
    counts = lead.groupBy(*group, "bin").agg(F.count(F.lit(1)).alias("rows"), F.min("lead").alias("lo"), F.max("lead").alias("hi"))
    along = Window.partitionBy(*group).orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    # thin bins share a tile, thick ones are cut into parts
    counts = scratch.keep(counts.withColumn("tile", F.floor(F.coalesce(F.sum("rows").over(along), F.lit(0)) / tile).cast("int")).withColumn("parts", F.greatest(F.lit(1), F.ceil(F.col("rows") / tile)).cast("int")), "bins")
    tiles = counts.groupBy(*group, "tile").agg(F.max("parts").alias("parts"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    tiles = scratch.keep(tiles.select(*group, "lo", "hi", "tile", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")), "tiles")
    reach = float(np.sqrt(max(0.0, 2 - 2 * least))) + 1e-6
    a, b = tiles.alias("a"), tiles.alias("b")
    order = F.struct("a.tile", "a.part") <= F.struct("b.tile", "b.part")
    pairs = a.join(b, (F.col("a.label") == F.col("b.label")) & (F.col("a.dims") == F.col("b.dims")) & order & (F.col("b.lo") - F.col("a.hi") <= reach) & (F.col("a.lo") - F.col("b.hi") <= reach))
    name = F.concat_ws(":", F.col("a.label"), F.col("a.dims"), F.col("a.tile"), F.col("a.part"), F.col("b.tile"), F.col("b.part"))
    same = (F.col("a.tile") == F.col("b.tile")) & (F.col("a.part") == F.col("b.part"))
    one = lambda t, k: F.struct(F.col(f"{t}.label").alias("l"), F.col(f"{t}.dims").alias("d"), F.col(f"{t}.tile").alias("t"), F.col(f"{t}.part").alias("p"), F.lit(k).alias("side"))
    sides = pairs.select(name.alias("task"), F.explode(F.when(same, F.array(one("a", 0))).otherwise(F.array(one("a", 1), one("b", 2)))).alias("x")).select("task", "x.*")
    binned = counts.select(F.col("label").alias("cl"), F.col("dims").alias("cd"), F.col("bin").alias("cb"), "tile", "parts")
    rows = lead.join(small_side(binned), (F.col("label") == F.col("cl")) & (F.col("dims") == F.col("cd")) & (F.col("bin") == F.col("cb"))).withColumn("part", F.pmod(F.xxhash64("key"), F.col("parts").cast("long")).cast("int"))
    sides = scratch.keep(sides, "sides")
    sent = rows.join(small_side(sides), (F.col("label") == F.col("l")) & (F.col("dims") == F.col("d")) & (F.col("tile") == F.col("t")) & (F.col("part") == F.col("p"))).select("task", "side", "key", "n", "v")

    def compare(batches):
        import pyarrow as pa

        held, task = [], None

        def work():
            side = np.array([r[0] for r in held])
            keys, n = np.array([r[1] for r in held], dtype=object), np.array([r[2] for r in held], dtype=np.int64)
            v = np.array([r[3] for r in held], dtype=np.float64)
            t = _turn(v, turned.value)
            if (side == 0).all():
                i, j = _pairs(v, t, np.arange(len(v)), None, least)
            else:
                i, j = _pairs(v, t, np.flatnonzero(side == 1), np.flatnonzero(side == 2), least)
            if not len(i):
                return
            near = np.bincount(i, weights=n[j], minlength=len(n)) + np.bincount(j, weights=n[i], minlength=len(n))
            root, hit = _roots(len(n), i, j), np.flatnonzero(near)
            tied = np.flatnonzero(root != np.arange(len(n)))
            yield pa.record_batch([pa.array(list(keys[hit]) + list(keys[tied]), pa.string()), pa.array([None] * len(hit) + list(keys[root[tied]]), pa.string()), pa.array(np.concatenate([near[hit], np.zeros(len(tied))]).astype(np.int64))], names=["a", "b", "w"])

        for batch in batches:
            for lo in range(0, batch.num_rows, TILE):
                for t, *rest in zip(*(c.to_pylist() for c in batch.slice(lo, TILE).columns)):
                    if t != task:
                        if held:
                            yield from work()
                        held, task = [], t
                    held.append(rest)
        if held:
            yield from work()

    return sent.repartition("task").sortWithinPartitions("task").mapInArrow(compare, "a string, b string, w long")
