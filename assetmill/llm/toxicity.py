"""Toxicity by logistic regression with the FTRL-proximal rule over hashed word features.

Features are the distinct words, word pairs and pairs that skip one word of a whole text, hashed into
a fixed number of cells. Every coordinate has its own learning rate, and the L1 term leaves most
weights at exactly zero, so the few others are sent to the executors.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assetmill.llm.batches import map_rows, raw_text
from assetmill.plans.ship import ship

CELLS = 1 << 20
#: Labelled rows that the weights are fitted on, the first by a hash of doc_id.
FIT_ROWS = 12_000
EPOCHS = 3
ALPHA, BETA, L1, L2 = 0.5, 1.0, 2.0, 1.0

_WORDS = re.compile(rb"[a-z0-9\x80-\xff]+")
#: Hashes of words that a worker remembers.
CACHED_WORDS = 300_000


class Features:
    """Cells of a text's features; words are runs of ASCII letters, digits and other bytes above 127."""

    def __init__(self):
        self.known: dict[bytes, int] = {}

    def __call__(self, buf: bytes) -> np.ndarray:
        words = _WORDS.findall(buf.lower())
        known = self.known
        if len(known) > CACHED_WORDS:
            known.clear()
        ids = []
        for w in words:
            h = known.get(w)
            if h is None:
                h = known[w] = zlib.crc32(w) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF
            ids.append(h)
        x = np.array(ids, dtype=np.uint64)
        parts = [x]
        for gap, salt in ((1, 0xC2B2AE3D27D4EB4F), (2, 0x165667B19E3779F9)):
            if len(x) > gap:
                parts.append((x[:-gap] * np.uint64(3) + x[gap:] * np.uint64(salt)) * np.uint64(0x9FB21C651E98DF25))
        return (np.concatenate(parts) >> np.uint64(44)).astype(np.int64)


def train(rows: list[tuple[np.ndarray, int]], epochs: int = EPOCHS) -> tuple[np.ndarray, float]:
    """Weights of all cells and the bias, from (distinct cells, label) in the order given."""
    z, n = np.zeros(CELLS + 1), np.zeros(CELLS + 1)
    for _ in range(epochs):
        for cells, label in rows:
            i = np.append(cells, CELLS)
            w = _weights(z[i], n[i])
            g = 1.0 / (1.0 + np.exp(-min(35.0, max(-35.0, w.sum())))) - label
            more = n[i] + g * g
            z[i] += g - (np.sqrt(more) - np.sqrt(n[i])) / ALPHA * w
            n[i] = more
    w = _weights(z, n)
    return w[:-1].astype(np.float32), float(w[-1])


def _weights(z: np.ndarray, n: np.ndarray) -> np.ndarray:
    return np.where(np.abs(z) <= L1, 0.0, -(z - np.sign(z) * L1) / ((BETA + np.sqrt(n)) / ALPHA + L2))


def _distinct_weights(table: np.ndarray, cells: np.ndarray) -> np.ndarray:
    """Weights of the distinct cells; only cells with a weight need to be told apart."""
    weights = table[cells]
    return table[np.unique(cells[weights != 0])]


def fold(doc_id: Column) -> Column:
    """crc32 of the id's text modulo 5; 0 marks rows held out. A null id is not held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5, F.lit(1))


def fit(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS) -> tuple[np.ndarray, np.ndarray, float]:
    """Cells with a weight, their weights, and the bias. Labels of held-out rows are never read into the
    fit. Texts become cells where they are scanned; the ``rows`` first of these, by a hash of doc_id and
    among equal ids by their cells, go to one task that fits them in that order."""
    ship(docs.sparkSession)
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & (fold(F.col("doc_id")) != 0)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    turn = F.md5(F.concat(F.lit("fit:"), F.col("doc_id").cast("string")))
    chosen = known.orderBy(turn, "doc_id").limit(rows)
    sample = docs.join(F.broadcast(chosen), "doc_id").select(turn.alias("turn"), "doc_id", "toxic", raw_text().alias("text"))

    def features(batches):
        import pyarrow as pa

        from assetmill.llm.batches import slices

        make = Features()
        for turns, _, labels_, texts in slices(batches):
            yield pa.record_batch([pa.array(turns, pa.string()), pa.array(labels_, pa.int32()), pa.array([np.unique(make(t)).astype(np.int32).tobytes() for t in texts], pa.binary())], names=["turn", "toxic", "cells"])

    def learn(batches):
        import pyarrow as pa

        got = []
        for batch in batches:
            turns, ys, cells = (c.to_pylist() for c in batch.columns)
            got += [(np.frombuffer(c, dtype=np.int32), int(y)) for c, y in zip(cells, ys)]
        w, bias = train(got)
        used = np.flatnonzero(w)
        yield pa.record_batch([pa.array(np.append(used, CELLS), pa.int32()), pa.array(np.append(w[used], bias).astype(np.float64), pa.float64())], names=["cell", "weight"])

    ready = sample.select("turn", "doc_id", F.col("toxic").cast("int").alias("toxic"), "text").mapInArrow(features, "turn string, toxic int, cells binary")
    got = ready.orderBy("turn", "cells").limit(rows).mapInArrow(learn, "cell int, weight double").toPandas()
    cells, weights = got["cell"].to_numpy(), got["weight"].to_numpy()
    body = cells != CELLS
    return cells[body].astype(np.int32), weights[body].astype(np.float32), float(weights[~body][0]) if (~body).any() else 0.0


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray, float]) -> DataFrame:
    """doc_id, held_out, score (0 to 1, higher is more likely toxic), predicted.

    The score depends on the whole text alone; null texts count as empty and score by the bias; equal
    texts score the same; an empty table gives no rows. Other columns are not read.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        cells, weights, bias = sent.value
        table = np.zeros(CELLS, dtype=np.float32)
        table[cells] = weights
        features = Features()

        def one(doc_id, held_out, buf):
            hit = _distinct_weights(table, features(buf))
            s = float(1.0 / (1.0 + np.exp(-min(35.0, max(-35.0, float(hit.sum(dtype=np.float64)) + bias)))))
            return doc_id, held_out, s, int(s >= 0.5)

        return one

    return map_rows(docs.select("doc_id", (fold(F.col("doc_id")) == 0).alias("held_out"), raw_text()), make, "doc_id long, held_out boolean, score double, predicted int")
