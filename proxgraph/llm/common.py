"""Shared helpers: tables in the shared folder, guarded broadcasts, Arrow columns, vectorised words.

Word hashes are 64-bit sums ``value(byte) * R**position`` (arithmetic modulo 2**64) that are
finished with a bit mixer, so a whole block of documents is hashed with a few numpy calls.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship

#: Rows up to which a side may be broadcast; beyond it the same join is shuffled.
BROADCAST_ROWS = 1_000_000
BROADCAST_BYTES = 24 << 20
#: Rows of an Arrow batch.
ARROW_ROWS = 2000

WHITE = b"\t\n\x0b\x0c\r "


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


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


def saved(df: DataFrame) -> DataFrame:
    """``df`` as a Parquet table in the shared folder: its lineage ends there and every executor can read it."""
    path = f"{shared_folder(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def arrow_map(df: DataFrame, function, schema: str) -> DataFrame:
    """``mapInArrow`` with this package made importable in the workers.

    Texts come in batches of at most ``ARROW_ROWS`` rows, which bounds a worker's memory.
    """
    spark = df.sparkSession
    ship(spark)
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > ARROW_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))
    return df.mapInArrow(function, schema)


def join_bounded(big: DataFrame, small: DataFrame, on, how: str, rows: int, row_bytes: int = 24) -> DataFrame:
    """Join with ``small`` broadcast when ``rows * row_bytes`` is under the bound, else shuffled."""
    if rows <= BROADCAST_ROWS and rows * row_bytes <= BROADCAST_BYTES:
        small = F.broadcast(small)
    return big.join(small, on, how)


def drop_rows(docs: DataFrame, bad: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``docs`` without the rows whose (id, text) is in ``bad`` (id, text_hash); null ids and texts are values."""
    bad = saved(bad.select(F.col("id").alias("_px_id"), F.col("text_hash").alias("_px_hash")).distinct())
    on = docs[id_col].cast("long").eqNullSafe(F.col("_px_id")) & (F.xxhash64(docs[text_col].cast("string")) == F.col("_px_hash"))
    return join_bounded(docs, bad, on, "left_anti", bad.count())


def binary_column(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """Values as bytes, nulls as empty."""
    return [b"" if x is None else x for x in batch.column(name).to_pylist()]


def blocks(column: pa.Array, limit: int = 2 << 20) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, row after the last, bytes, offsets) of pieces of a binary column, nulls as empty.

    A piece holds at most ``limit`` bytes, or one row.
    """
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.fill_null(b"") if column.null_count else column
    wide = pa.types.is_large_binary(column.type)
    _, places, data = column.buffers()
    offs = np.frombuffer(places, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    lo, n = 0, len(column)
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + limit, "right")) - 1)
        hi = min(hi, n)
        yield lo, hi, raw[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
        lo = hi


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    base = np.full(n, MULTIPLIER, np.uint64)
    back = np.full(n, INVERSE, np.uint64)
    base[0] = back[0] = 1
    return np.multiply.accumulate(base), np.multiply.accumulate(back)


MULTIPLIER = 0x9E3779B97F4A7C15
INVERSE = pow(MULTIPLIER, -1, 1 << 64)
_POWERS: list[np.ndarray] = [np.zeros(0, np.uint64), np.zeros(0, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """R**i and R**-i modulo 2**64 for i < n; kept for the process."""
    if len(_POWERS[0]) < n:
        _POWERS[:] = _power_tables(max(n, 1 << 16))
    return _POWERS[0][:n], _POWERS[1][:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective mixer of 64-bit values (shifts and odd multipliers)."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def _byte_values(lower: bool) -> np.ndarray:
    values = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    if lower:
        values[65:91] = values[97:123]
    values[list(WHITE)] = 0
    return values


_VALUES = {False: _byte_values(False), True: _byte_values(True)}
_IS_WHITE = np.zeros(256, bool)
_IS_WHITE[list(WHITE)] = True


def word_hashes(raw: np.ndarray, offs: np.ndarray, lower: bool) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the white-space words of a block, and each document's bounds in that array."""
    if not len(raw):
        return np.zeros(0, np.uint64), np.zeros(len(offs), np.int64)
    white = _IS_WHITE[raw]
    begins = ~white
    begins[1:] &= white[:-1]
    heads = offs[:-1][offs[:-1] < len(raw)]
    begins[heads] |= ~white[heads]
    starts = np.flatnonzero(begins)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(len(offs), np.int64)
    up, down = powers(len(raw))
    sums = np.add.reduceat(_VALUES[lower][raw] * up, starts) * down[starts]
    return mix(sums), np.searchsorted(starts, offs)


def signed(a: np.ndarray) -> np.ndarray:
    return a.view(np.int64)
