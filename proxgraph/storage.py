"""Tables in the folder that all executors share, and bounded broadcasts."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid
from urllib.parse import unquote, urlparse

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a side may be broadcast; beyond it the same join is shuffled.
BROADCAST_ROWS = 1_000_000
BROADCAST_BYTES = 48 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; only a local session that has none gets a temporary one."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not sc.master.startswith("local[") and sc.master != "local":
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="proxgraph-checkpoint-")
            atexit.register(shutil.rmtree, folder, True)
        sc.setCheckpointDir(folder)
    return sc.getCheckpointDir()


#: Removes the shuffle files of a query when it has ended, instead of when the driver collects its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def shuffles_removed(spark: SparkSession):
    """Queries that are begun inside leave no shuffle files."""
    before = spark.conf.get(CLEANUP)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP, before)


def saved(df: DataFrame, codec: str = "snappy") -> DataFrame:
    """``df`` as a Parquet table in the shared folder: its lineage and shuffle files end there and every executor can read it."""
    path = f"{shared_folder(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    with shuffles_removed(df.sparkSession):
        df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def local_path(folder: str) -> str | None:
    """The path of a folder or file that is reached as files, else none."""
    at = urlparse(folder)
    return unquote(at.path) if at.scheme in ("", "file") else None


def files(table: DataFrame) -> list[str]:
    """The files of a table of the shared folder, which must be one of files."""
    return sorted(local_path(f) for f in table.inputFiles())


def column(table: DataFrame, name: str) -> np.ndarray:
    """A column of a table of the shared folder without its rows' way through the JVM; rows of equal calls are in one order."""
    held = [pq.read_table(f, columns=[name]).column(0) for f in files(table)]
    return pa.chunked_array([c for x in held for c in x.chunks], held[0].type).to_numpy() if held else np.zeros(0, np.int64)


def join_bounded(big: DataFrame, small: DataFrame, on, how: str, rows: int, row_bytes: int = 24) -> DataFrame:
    """Join with ``small`` broadcast when ``rows * row_bytes`` is under the bound, else shuffled."""
    if rows <= BROADCAST_ROWS and rows * row_bytes <= BROADCAST_BYTES:
        small = F.broadcast(small)
    return big.join(small, on, how)
