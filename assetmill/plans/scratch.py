"""Tables that cut lineage.

Everything here is written to the folder the cluster names in ``spark.checkpoint.dir``,
which all executors share, so that the loss of an executor costs no recomputation.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}


def scratch_root(spark: SparkSession) -> str:
    """The shared folder of the session; only where none is set, one temporary folder a process (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        with contextlib.suppress(Exception):
            named = spark.sparkContext.getCheckpointDir()
    if not named:
        master = spark.sparkContext.master
        if not (master == "local" or master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        named = _LOCAL.setdefault("dir", "file://" + tempfile.mkdtemp(prefix="assetmill-"))
    return named.rstrip("/")


class Scratch:
    """A folder of written tables that one operator call owns.

    ``keep`` writes a table and reads it back with its schema; ``drop`` removes tables that later
    ones no longer need; leaving the ``with`` block on an error removes them all. What the returned
    DataFrame still reads stays until the session's owner clears the shared folder.
    """

    def __init__(self, spark: SparkSession, tag: str):
        self.spark = spark
        self.root = f"{scratch_root(spark)}/{tag}-{uuid.uuid4().hex[:12]}"
        self.turns: dict[str, int] = {}

    def path(self, name: str) -> str:
        """Where the latest table of this name is."""
        return f"{self.root}/{name}.{self.turns.get(name, 0)}" if name else self.root

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        self.turns[name] = self.turns.get(name, 0) + 1
        target = self.path(name)
        df.write.mode("errorifexists").parquet(target)
        return self.spark.read.schema(df.schema).parquet(target)

    def drop(self, *names: str) -> None:
        jvm = self.spark._jvm
        for name in names:
            place = jvm.org.apache.hadoop.fs.Path(self.path(name))
            place.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(place, True)

    def __enter__(self) -> "Scratch":
        return self

    def __exit__(self, kind, value, trace) -> None:
        if kind is not None:
            with contextlib.suppress(Exception):
                self.drop("")
