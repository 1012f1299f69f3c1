"""Tables written to the folder that driver and executors share, to cut lineage."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Bytes of a file of a table whose size is known before it is written.
PIECE_BYTES = 1 << 20
_own: list[str] = []
_open = threading.local()  # .scopes: the tables settled within each running settle_last


def folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir as the cluster names it; a folder of this machine only where it is unset and the master is local, as in tests."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="planner-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return f"file://{_own[0]}"


def pieced(df: DataFrame, size: int | None) -> DataFrame:
    """df of about so many bytes in at most as many partitions as these bytes and twice all cores call for; None: as it is.

    A small table is otherwise written as a file for each shuffle partition, and each file costs more than its rows.
    """
    if size is None:
        return df
    return df.coalesce(max(2 * df.sparkSession.sparkContext.defaultParallelism, -(-size // PIECE_BYTES)))


class Settled:
    """A written table; `drop` frees its files once nothing reads them any more. size: its bytes, roughly, if they are known."""

    def __init__(self, df: DataFrame, size: int | None = None):
        self.spark = df.sparkSession
        self.path = f"{folder(self.spark)}/table-{uuid.uuid4().hex}"
        pieced(df, size).write.parquet(self.path)
        self.df = self.spark.read.schema(df.schema).parquet(self.path)
        if getattr(_open, "scopes", None):
            _open.scopes[-1].append(self)

    def drop(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def settle(df: DataFrame, size: int | None = None) -> DataFrame:
    return Settled(df, size).df


@contextmanager
def dropped() -> Iterator[None]:
    """Tables settled within are dropped at the end: for answers that are on the driver by then. Each thread has its own."""
    if not hasattr(_open, "scopes"):
        _open.scopes = []
    _open.scopes.append([])
    try:
        yield
    finally:
        for table in _open.scopes.pop():
            table.drop()


def settle_last(make: Callable[[], DataFrame]) -> DataFrame:
    """What `make` gives, written; the tables settled on the way are dropped, since only the written one is read from now on."""
    if not hasattr(_open, "scopes"):
        _open.scopes = []
    _open.scopes.append([])
    out = None
    try:
        out = Settled(make())
    finally:
        for table in _open.scopes.pop():
            if table is not out:
                table.drop()
    if _open.scopes:
        _open.scopes[-1].append(out)
    return out.df
