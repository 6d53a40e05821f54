"""Shared pieces of the operators that work document by document in Arrow batches."""

from __future__ import annotations

import contextlib
import gc
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assetmill.plans.ship import ship

#: Rows, and bytes of text, that become Python objects at a time; a longer text goes alone.
SLICE, SLICE_BYTES = 512, 1 << 20


def raw_text(column: str = "text") -> Column:
    """A text as UTF-8 bytes; null counts as empty."""
    return F.coalesce(F.col(column), F.lit("")).cast("binary")


def slices(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, ...]]:
    """The columns of a few rows at a time, as lists."""
    for batch in batches:
        long = [c for c in batch.columns if pa.types.is_binary(c.type) or pa.types.is_string(c.type)]
        size = sum((pc.fill_null(pc.binary_length(c), 0).to_numpy(zero_copy_only=False).astype(np.int64) for c in long), np.zeros(batch.num_rows, dtype=np.int64))
        end, at = np.cumsum(size), 0
        while at < batch.num_rows:
            fits = int(np.searchsorted(end, (end[at - 1] if at else 0) + SLICE_BYTES, side="right"))
            stop = min(max(fits, at + 1), at + SLICE)
            yield tuple(c.to_pylist() for c in batch.slice(at, stop - at).columns)
            at = stop


def arrow_schema(ddl: str) -> pa.Schema:
    kinds = {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "boolean": pa.bool_(), "binary": pa.binary(), "float": pa.float32(), "array<double>": pa.list_(pa.float64()), "array<int>": pa.list_(pa.int32())}
    return pa.schema([pa.field(n, kinds[k]) for n, k in (x.strip().split(" ") for x in ddl.split(","))])


_HELD: dict[str, dict] = {}


def _return_freed() -> None:
    """Give freed memory back to the system where the C library can."""
    import ctypes

    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def tidy(run: Callable) -> Callable:
    """``run`` over the batches of a task, after which the worker gives back what it does not use."""

    def whole(batches):
        yield from run(batches)
        _return_freed()

    return whole


def held(owner: str) -> dict:
    """What an operator keeps in this worker between tasks; what others keep is freed."""
    others = [kept for name, kept in _HELD.items() if name != owner and kept]
    for kept in others:
        kept.clear()
    if others:
        gc.unfreeze()
        gc.collect()
        _return_freed()
    return _HELD.setdefault(owner, {})


@contextlib.contextmanager
def no_walks():
    """The collector rests: it would walk all that a slice makes, again and again, where nothing is a cycle."""
    was = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if was:
            gc.enable()


def map_slices(df: DataFrame, make: Callable[[], Callable[..., Iterable[tuple]]], ddl: str, owner: str = "") -> DataFrame:
    """A few rows of ``df`` at a time, given column by column to the function that ``make`` returns (made once a
    task), become rows with the columns of ``ddl``. ``owner`` names what ``make`` keeps by ``held``."""
    ship(df.sparkSession)

    def run(batches):
        held(owner)
        some, schema = make(), arrow_schema(ddl)
        for columns in slices(batches):
            with no_walks():
                out = list(some(*columns))
                made = [pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)] if out else []
            del columns, out
            yield from made

    return df.mapInArrow(tidy(run), ddl)


def map_rows(df: DataFrame, make: Callable[[], Callable[..., tuple]], ddl: str, owner: str = "") -> DataFrame:
    """``map_slices`` where each row, its columns given in order to the function that ``make`` returns, becomes
    one row."""

    def some():
        one = make()
        return lambda *columns: (one(*row) for row in zip(*columns))

    return map_slices(df, some, ddl, owner)
