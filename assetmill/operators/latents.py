"""Hook for a frozen picture tokenizer: batches in, latents out, and back."""

from __future__ import annotations

from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from assetmill.plans.ship import ship


class LatentCodec(Protocol):
    """Both ways work on (rows, values) arrays; a codec is sent to the workers once a task."""

    def encode(self, x: np.ndarray) -> np.ndarray: ...

    def decode(self, z: np.ndarray) -> np.ndarray: ...


class Identity:
    """Stand-in codec: latents are the values."""

    def encode(self, x):
        return x

    def decode(self, z):
        return z


def apply(df: DataFrame, key: str, column: str, codec: LatentCodec, back: bool = False) -> DataFrame:
    """``key`` and the encoded (``back``: decoded) column, as doubles. Arrays of one batch have one length."""
    ship(df.sparkSession)
    schema = pa.schema([pa.field(key, pa.int64()), pa.field(column, pa.list_(pa.float64()))])

    def run(batches):
        for b in batches:
            if b.num_rows:
                x = np.array(b.column(1).to_pylist(), dtype=np.float64)
                y = codec.decode(x) if back else codec.encode(x)
                yield pa.record_batch([b.column(0).cast(pa.int64()), pa.array(list(y), pa.list_(pa.float64()))], schema=schema)

    return df.select(key, column).mapInArrow(run, f"{key} long, {column} array<double>")
