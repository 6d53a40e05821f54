"""Near duplicates by SimHash, searched through popcounts of short segments.

A 64-bit fingerprint is cut into 32 segments of two bits; the number of set bits in each gives a point
with 32 small coordinates. Flipping one bit moves one coordinate by one, so the Manhattan distance of
two points never exceeds the number of differing bits. Within 4 bits, one half of the coordinates is
within distance 2, and two such halves have a lattice point at distance 1 or less from both: each
fingerprint stands in the cells of all points within distance 1 of each of its halves, and linked
fingerprints meet in a cell. Pairs in a cell are then compared exactly, on all 64 bits.

Equal fingerprints are one node. A cell gives a spanning forest of its links, not all of them, and
cells beyond a fixed size are compared in blocks by other tasks, so no group's size is a limit.
"""

from __future__ import annotations

import re
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assetmill.llm.batches import map_rows, raw_text, tidy
from assetmill.operators.components import components, spread
from assetmill.plans.scratch import Scratch
from assetmill.plans.ship import ship

SEED = 42
MOST_BITS = 4
#: Fingerprints that one task compares with each other in one piece.
BLOCK = 2048
_WORDS = re.compile(rb"[^\x20\x09-\x0D]+")


def fingerprint(buf: bytes, shingle: int = 4) -> int:
    """SimHash of the word shingles of a text, with repeats, as a signed 64-bit number."""
    from xxhash import xxh64_intdigest

    words = _WORDS.findall(buf.lower())  # bytes: only A-Z change
    n = len(words)
    if not n:
        return 0
    if n < shingle:
        hashes = [xxh64_intdigest(b" ".join(words), SEED)]
    else:
        join = b" ".join
        hashes = [xxh64_intdigest(join(words[i : i + shingle]), SEED) for i in range(n - shingle + 1)]
    return of_hashes(np.array(hashes, dtype="<u8"))


def of_hashes(h: np.ndarray) -> int:
    """A bit is set if it is in over half of ``h``; zero without any."""
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(h), 1 << 15):
        ones += np.unpackbits(h[at : at + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view("<i8")[0])


def forest(points: np.ndarray, near: Callable[[int, np.ndarray], np.ndarray]) -> list[tuple[int, int]]:
    """Edges that connect what ``near`` links among the indices of ``points``, one less than each group."""
    left, edges = np.arange(len(points)), []
    while len(left) > 1:
        stack, left = [int(left[0])], left[1:]
        while stack and len(left):
            i = stack.pop()
            hit = near(i, left)
            new = left[hit]
            if len(new):
                edges += [(i, int(j)) for j in new]
                left = left[~hit]
                stack += new.tolist()
    return edges


def _links_in(points: np.ndarray) -> list[tuple[int, int]]:
    return forest(points, lambda i, js: np.bitwise_count(points[js] ^ points[i]) <= MOST_BITS)


def _edge_batch(kind: int, a: np.ndarray, b: np.ndarray):
    import pyarrow as pa

    return pa.record_batch([pa.array(np.full(len(a), kind, dtype=np.int32)), pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["kind", "a", "b"])


def _compare_cells(batches, block: int):
    """Rows (cell, fp) sorted by cell: links (kind 0), and the rows of cells over ``block`` (kind 1)."""
    held_cell, held_fp = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.uint64)
    over: int | None = None

    def work(cell: np.ndarray, fp: np.ndarray):
        starts = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
        sizes = np.diff(np.append(starts, len(cell)))
        run = np.repeat(sizes, sizes)
        few = run <= 16
        found_a, found_b = [], []
        for gap in range(1, 16):
            if len(cell) <= gap:
                break
            i = np.flatnonzero((cell[gap:] == cell[:-gap]) & few[gap:])
            if not len(i):
                break
            i = i[np.bitwise_count(fp[i] ^ fp[i + gap]) <= MOST_BITS]
            found_a.append(fp[i])
            found_b.append(fp[i + gap])
        for at, size in zip(starts[sizes > 16], sizes[sizes > 16]):
            points = fp[at : at + size]
            if edges := _links_in(points):
                pair = np.array(edges)
                found_a.append(points[pair[:, 0]])
                found_b.append(points[pair[:, 1]])
        if found_a and sum(map(len, found_a)):
            pairs = np.unique(np.stack([np.concatenate(found_a), np.concatenate(found_b)], axis=1), axis=0)
            yield _edge_batch(0, np.ascontiguousarray(pairs[:, 0]), np.ascontiguousarray(pairs[:, 1]))

    for batch in batches:
        cell = np.concatenate([held_cell, batch.column(0).to_numpy()])
        fp = np.concatenate([held_fp, batch.column(1).to_numpy().view(np.uint64)])
        if not len(cell):
            continue
        if over is not None:  # the rest of a cell that is too large goes on to the second step
            same = cell == over
            if same.any():
                yield _edge_batch(1, cell[same], fp[same])
                cell, fp = cell[~same], fp[~same]
            if len(cell):
                over = None
            else:
                held_cell, held_fp = cell, fp
                continue
        last = np.searchsorted(cell, cell[-1]) if len(cell) and (cell[1:] >= cell[:-1]).all() else int(np.flatnonzero(cell != cell[-1])[-1] + 1) if (cell != cell[-1]).any() else 0
        held_cell, held_fp = cell[last:], fp[last:]
        cell, fp = cell[:last], fp[:last]
        if len(held_cell) > block:
            over = int(held_cell[0])
            yield _edge_batch(1, held_cell, held_fp)
            held_cell, held_fp = held_cell[:0], held_fp[:0]
        if len(cell):
            yield from _split_large(cell, fp, work, block)
    if len(held_cell):
        yield from _split_large(held_cell, held_fp, work, block)


def _split_large(cell, fp, work, block):
    starts = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
    sizes = np.diff(np.append(starts, len(cell)))
    large = np.repeat(sizes > block, sizes)
    if large.any():
        yield _edge_batch(1, cell[large], fp[large])
        cell, fp = cell[~large], fp[~large]
    if len(cell):
        yield from work(cell, fp)


def _compare_blocks(batches):
    """Rows (task, fp) sorted by task: links of each task's rows."""
    held_task, held_fp = None, []

    def work():
        points = np.unique(np.concatenate(held_fp))
        if edges := _links_in(points):
            pair = np.array(edges)
            yield _edge_batch(0, points[pair[:, 0]], points[pair[:, 1]])

    for batch in batches:
        task, fp = batch.column(0).to_pylist(), batch.column(1).to_numpy().view(np.uint64)
        at = 0
        while at < len(task):
            end = at
            while end < len(task) and task[end] == task[at]:
                end += 1
            if held_task is not None and task[at] != held_task:
                yield from work()
                held_fp = []
            held_task = task[at]
            held_fp.append(fp[at:end])
            at = end
    if held_fp:
        yield from work()


def links(prints: DataFrame, scratch: Scratch, block: int = BLOCK) -> DataFrame:
    """Links (a, b) among the distinct fingerprints of ``prints`` (column fp): enough of them that two
    fingerprints reach each other exactly if they do by pairs within ``MOST_BITS``. ``block`` changes no result."""
    ship(prints.sparkSession)
    cells = []
    for half in (0, 1):
        bits = F.shiftrightunsigned("fp", 32 * half).bitwiseAND(F.lit(0xFFFFFFFF))
        # popcounts of the sixteen two-bit segments, two bits each
        v = bits - F.shiftrightunsigned(bits, 1).bitwiseAND(F.lit(0x55555555))
        up = F.filter(F.array(*(F.when(F.shiftrightunsigned(v, 2 * i).bitwiseAND(F.lit(3)) < 2, v + F.lit(1 << 2 * i)) for i in range(16))), lambda x: x.isNotNull())
        down = F.filter(F.array(*(F.when(F.shiftrightunsigned(v, 2 * i).bitwiseAND(F.lit(3)) > 0, v - F.lit(1 << 2 * i)) for i in range(16))), lambda x: x.isNotNull())
        own = F.concat(F.array(v), up, down)
        cells.append(F.transform(own, lambda x: x.bitwiseOR(F.lit(1 << 32))) if half else own)
    placed = prints.select("fp").select(F.explode(F.concat(*cells)).alias("cell"), "fp")
    found = scratch.keep(placed.repartition("cell").sortWithinPartitions("cell").mapInArrow(tidy(lambda batches: _compare_cells(batches, block)), "kind int, a long, b long"), "found")
    large = found.where("kind = 1").select(F.col("a").alias("cell"), F.col("b").alias("fp"))
    sizes = large.groupBy("cell").agg(F.ceil(F.count(F.lit(1)) / F.lit(block // 2)).cast("int").alias("parts")).withColumnRenamed("cell", "c")
    part = F.pmod(F.xxhash64("fp", F.lit("part")), F.col("parts").cast("long")).cast("int")
    tasks = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda k: F.concat_ws(":", F.col("cell"), F.least(k, F.col("part")), F.greatest(k, F.col("part"))))
    blocks = large.join(sizes, large.cell == sizes.c).withColumn("part", part).select(F.explode(tasks).alias("task"), "fp")
    more = blocks.repartition("task").sortWithinPartitions("task").mapInArrow(_compare_blocks, "kind int, a long, b long")
    return found.where("kind = 0").select("a", "b").union(more.select("a", "b")).distinct()


def near_duplicates(docs: DataFrame, scratch: Scratch, shingle: int = 4) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (the smallest doc_id that
    links reach, itself included), copies (rows with the same fingerprint).

    Texts are lower-cased in A-Z only and read whole; words are runs of anything but space and the
    controls 9 to 13. A text with fewer words than a shingle is one shingle, one without words, and a
    null one, has fingerprint zero and links like any other. Equal rows keep their own rows; a null
    doc_id belongs to its class but names it only if the class has no other id; an empty table gives no
    rows. Other columns are not read.
    """
    rows = scratch.keep(map_rows(docs.select("doc_id", raw_text()), lambda: lambda i, buf: (i, fingerprint(buf, shingle)), "doc_id long, fp long"), "prints")
    classes = scratch.keep(rows.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("copies")), "classes")
    reach = components(links(classes, scratch), scratch)
    named = scratch.keep(classes.join(reach, classes.fp == reach.node, "left").select("fp", "first", "copies", F.coalesce("component", "fp").alias("root")), "named")
    known = scratch.keep(spread(named, "root", F.min("first"), "component_id").select(F.col("fp").alias("cfp"), "component_id", "copies"), "known")
    scratch.drop("found", "classes", "named")
    return rows.join(known, rows.fp == known.cfp).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id", "copies")
