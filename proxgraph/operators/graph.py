"""Graphs as edge tables with the hygiene that the walk needs.

``arcs`` has a row per directed arc with its place among the source's arcs (``idx``, by ``dst``) and
both ends' degrees.  A walk step is then one equi-join on (node, idx), which spreads a hub's arcs
over all partitions, and a push needs no further lookup of degrees.  ``pairs`` is the same without the
degree of ``dst``, which needs a join; it is all that the kernels' adjacency is made from.

The adjacency of the kernels is broadcast up to ``KERNEL_ARCS`` arcs.  Beyond, it lies in array files of the shared
folder, which tasks map into memory: a push or a walk reads the pages of the arcs it touches, and no process holds it.
"""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import ship
from ..storage import column, files, local_path, saved, shared_folder

#: Arcs up to which the adjacency may be collected and broadcast (16 bytes an arc).
KERNEL_ARCS = 5_000_000
#: Nodes up to which the adjacency may be stored: the driver sorts their ids and degrees, a kernel holds vectors of this length.
STORE_NODES = 12_000_000
#: Arcs that a task collects before it writes them.
STORE_BATCH = 2_000_000
#: Arcs of a node that the builder holds in memory.
HELD_ARCS = 1 << 22
#: Arcs of a packed run, of a piece that a task sorts at once, and of a batch of rows; rows that one sampled row stands for.
RUN_ARCS, PIECE_ARCS, BATCH_ARCS, SAMPLE_EVERY = 1 << 20, 1 << 20, 1 << 17, 1 << 12


class GraphError(ValueError):
    """An edge table that the walk is not defined on."""


def apply_dangling_policy(edges: DataFrame, policy: str) -> DataFrame:
    """Nodes without an out-arc: ``error``, ``self_loop``, or ``drop`` (until none is left)."""
    if policy == "drop":
        while True:
            kept = saved(edges.join(edges.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi").select("src", "dst"))
            if kept.count() == edges.count():
                return kept
            edges = kept
    bad = edges.select(F.col("dst").alias("src")).distinct().join(edges.select("src").distinct(), "src", "left_anti")
    if policy == "self_loop":
        return edges.unionByName(bad.select("src", F.col("src").alias("dst")))
    if policy != "error":
        raise ValueError("dangling must be error, self_loop or drop")
    if bad.limit(1).count():
        raise GraphError("some nodes have no out-arc; choose a dangling policy")
    return edges


@dataclass
class Csr:
    """Adjacency arrays for the kernels; node numbers are places in ``ids`` (sorted)."""

    ids: np.ndarray
    out_at: np.ndarray
    out_to: np.ndarray
    in_at: np.ndarray
    in_from: np.ndarray

    @property
    def out_deg(self) -> np.ndarray:
        return np.diff(self.out_at)

    @property
    def in_deg(self) -> np.ndarray:
        return np.diff(self.in_at)

    def place(self, ids) -> np.ndarray:
        at = np.searchsorted(self.ids, ids)
        if np.any(at >= len(self.ids)) or np.any(self.ids[np.minimum(at, len(self.ids) - 1)] != ids):
            raise GraphError("a node is not in the graph")
        return at


_OPEN: dict[str, Csr] = {}


@dataclass(frozen=True)
class StoredCsr:
    """The adjacency as array files of the shared folder; ``value`` maps them, once for a process."""

    folder: str
    symmetric: bool

    @property
    def value(self) -> Csr:
        if self.folder not in _OPEN:
            held = lambda name: np.load(f"{self.folder}/{name}.npy", mmap_mode="r")
            ids, out_at, out_to = np.array(held("ids")), np.array(held("out_at")), held("out_to")
            _OPEN.clear()  # a worker that is used again drops the graph before
            _OPEN[self.folder] = Csr(ids, out_at, out_to, *((out_at, out_to) if self.symmetric else (np.array(held("in_at")), held("in_from"))))
        return _OPEN[self.folder]


def _store_arcs(placed: DataFrame, near: str, far: str, idx: str, folder: str, name: str, starts: str, total: int) -> None:
    """``far`` ends of arcs, as places in ids.npy, in one file by (``near``, ``idx``).

    Tasks read files of the saved table ``placed``, whose rows would cost more on their way through the JVM, and write runs of neighbouring places, named by their first; the driver appends them to each other.
    """
    runs = Path(folder, f"{name}.runs")
    runs.mkdir()

    def write(parts: list[tuple[np.ndarray, np.ndarray]]) -> None:
        at, to = (np.concatenate(x) for x in zip(*parts))
        if np.any(at[1:] < at[:-1]):
            order = np.argsort(at, kind="stable")
            at, to = at[order], to[order]
        for lo, hi in zip(*(lambda cut: (np.concatenate(([0], cut)), np.concatenate((cut, [len(at)]))))(np.flatnonzero(np.diff(at) != 1) + 1)):
            partial = f"{runs}/.{uuid.uuid4().hex}"
            to[lo:hi].tofile(partial)
            os.replace(partial, f"{runs}/{at[lo]:015d}")

    def run(batches):
        ids, begin = np.load(f"{folder}/ids.npy"), np.load(f"{folder}/{starts}.npy")
        parts, count = [], 0
        places = None
        if len(ids) and int(ids[-1]) - int(ids[0]) < 8 * len(ids):
            places = np.zeros(int(ids[-1] - ids[0]) + 1, np.int32)
            places[ids - ids[0]] = np.arange(len(ids))
        place = lambda of: np.searchsorted(ids, of).astype(np.int32) if places is None else places[of - ids[0]]
        for batch in (b for given in batches for path in given.column(0).to_pylist() for b in pq.ParquetFile(path).iter_batches(BATCH_ARCS, columns=[near, far, idx])):
            x, y, i = (batch.column(k).to_numpy() for k in (near, far, idx))
            parts.append((begin[place(x)] + i, place(y)))
            count += len(x)
            if count >= STORE_BATCH:
                write(parts)
                parts, count = [], 0
        if count:
            write(parts)
        yield pa.RecordBatch.from_arrays([pa.array([], pa.int64())], names=["none"])

    paths = files(placed)
    spark = placed.sparkSession
    if paths:
        spark.createDataFrame([(x,) for x in paths], "path string").repartition(min(len(paths), 4 * spark.sparkContext.defaultParallelism)).mapInArrow(run, "none long").count()
    with open(f"{folder}/{name}.npy", "wb") as out:
        np.lib.format.write_array_header_1_0(out, {"descr": np.dtype(np.int32).str, "fortran_order": False, "shape": (total,)})
        done = 0
        for part in sorted(runs.iterdir()):
            if part.name.startswith("."):
                continue
            if int(part.name) != done:
                raise RuntimeError("the stored adjacency has a gap")
            done += part.stat().st_size // 4
            out.write(part.read_bytes())
            part.unlink()
        if done != total:
            raise RuntimeError("the stored adjacency is not whole")


class Graph:
    """Build one with ``Graph.from_edges``."""

    def __init__(self, arcs: DataFrame | None, directed: bool, pairs: DataFrame | None = None) -> None:
        self._arcs, self.directed, self._pairs, self._broadcast = arcs, directed, pairs, None

    @property
    def arcs(self) -> DataFrame:
        """(src, dst, idx, out_deg, dst_deg): idx from 0 in order of dst; dst_deg is the out-degree of dst."""
        if self._arcs is None:
            deg = self.nodes.select(F.col("id").alias("dst"), F.col("out_deg").alias("dst_deg"))
            self._arcs = saved(self._pairs.join(deg, "dst", "left").select("src", "dst", "idx", "out_deg", "dst_deg"))
        return self._arcs

    @property
    def pairs(self) -> DataFrame:
        """(src, dst, idx, out_deg)."""
        return self._arcs.drop("dst_deg") if self._pairs is None else self._pairs

    @classmethod
    def from_edges(cls, edges: DataFrame, directed: bool, dangling: str = "error", self_loops: str = "auto") -> "Graph":
        """From (src, dst) rows; rows with a null end are rejected, repeated rows count once.

        Undirected edges may be given in either or both orders; their self-loops are rejected
        unless ``self_loops`` is "drop".
        """
        e = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
        if directed:
            e = saved(e)
            if e.where("src is null or dst is null").limit(1).count():
                raise GraphError("an edge has a null end")
            e = apply_dangling_policy(e.where("src <> dst") if self_loops == "drop" else e, dangling)
        return cls(None, directed, saved(_placed(e, not directed, "keep" if directed else self_loops), "zstd"))

    @property
    def spark(self):
        return self.pairs.sparkSession

    @cached_property
    def nodes(self) -> DataFrame:
        """(id, out_deg, in_deg)."""
        out = self.pairs.where("idx = 0").select(F.col("src").alias("id"), "out_deg")
        if not self.directed:
            return saved(out.select("id", "out_deg", F.col("out_deg").alias("in_deg")))
        into = self.pairs.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("in_deg"))
        return saved(out.join(into, "id", "left").select("id", "out_deg", F.coalesce("in_deg", F.lit(0)).cast("long").alias("in_deg")))

    @cached_property
    def stats(self) -> dict:
        """n, m (an undirected edge counts once), arcs, dmax and dmin (of out-degrees)."""
        r = self.nodes.agg(F.count("*").alias("n"), F.sum("out_deg").alias("arcs"), F.max("out_deg").alias("dmax"), F.min("out_deg").alias("dmin")).first()
        arcs = r["arcs"] or 0
        return {"n": r["n"], "arcs": arcs, "m": arcs if self.directed else arcs // 2, "dmax": r["dmax"], "dmin": r["dmin"]}

    @property
    def n(self) -> int:
        return self.stats["n"]

    @property
    def m(self) -> int:
        return self.stats["m"]

    @cached_property
    def fits_kernel(self) -> bool:
        """Few arcs, or few enough nodes and a shared folder of files."""
        return self.stats["arcs"] <= KERNEL_ARCS or self.n <= STORE_NODES and local_path(shared_folder(self.spark)) is not None

    def use_kernel(self, engine: str) -> bool:
        if engine == "kernel":
            self._check_kernel()
        return engine == "kernel" or engine == "auto" and self.fits_kernel

    def _check_kernel(self) -> None:
        if not self.fits_kernel:
            raise GraphError(f"the kernel engine takes at most {KERNEL_ARCS} arcs, or {STORE_NODES} nodes with a shared folder of files")

    @property
    def csr(self):
        """The adjacency, broadcast or stored, behind the check of its size; ``value`` is a ``Csr``."""
        if self._broadcast is None:
            self._check_kernel()
            ship(self.spark)
            if self.stats["arcs"] > KERNEL_ARCS:
                self._broadcast = self._stored()
                return self._broadcast
            t = self.pairs.select("src", "dst").toArrow()
            src, dst = t.column("src").to_numpy(), t.column("dst").to_numpy()
            ids = np.unique(np.concatenate([src, dst]))
            s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
            o, i = np.lexsort((d, s)), np.lexsort((s, d))
            at = lambda x: np.concatenate(([0], np.cumsum(np.bincount(x, minlength=len(ids)))))
            self._broadcast = self.spark.sparkContext.broadcast(Csr(ids, at(s), d[o], at(d), s[i]))
        return self._broadcast

    def _stored(self) -> StoredCsr:
        folder = f"{local_path(shared_folder(self.spark))}/adjacency/{uuid.uuid4().hex}"
        os.makedirs(folder)
        ids = column(self.nodes, "id")
        order = np.argsort(ids)
        np.save(f"{folder}/ids.npy", ids[order])
        for side, deg in (("out", "out_deg"),) if not self.directed else (("out", "out_deg"), ("in", "in_deg")):
            np.save(f"{folder}/{side}_at.npy", np.concatenate(([0], np.cumsum(column(self.nodes, deg)[order]))))
        placed = self.pairs if self._pairs is not None else saved(self.pairs.repartitionByRange("src").sortWithinPartitions("src", "idx"))
        _store_arcs(placed, "src", "dst", "idx", folder, "out_to", "out_at", self.stats["arcs"])
        if self.directed:
            into = self.pairs.select("src", "dst").repartitionByRange("dst")
            into = saved(into.withColumn("idx", F.row_number().over(Window.partitionBy("dst").orderBy("src")).cast("long") - 1))
            _store_arcs(into, "dst", "src", "idx", folder, "in_from", "in_at", self.stats["arcs"])
        return StoredCsr(folder, not self.directed)

    def require(self, node: int) -> None:
        if not self.nodes.where(F.col("id") == node).limit(1).count():
            raise GraphError(f"node {node} is not in the graph")

    def subgraph(self, nodes: DataFrame, dangling: str = "drop") -> "Graph":
        """Induced on ``nodes`` (id)."""
        keep = nodes.select("id").distinct()
        e = self.pairs.select("src", "dst").join(keep.withColumnRenamed("id", "src"), "src", "left_semi").join(keep.withColumnRenamed("id", "dst"), "dst", "left_semi")
        return Graph.from_edges(e, self.directed, dangling=dangling)

    def sample_edges(self, share: float, seed: int = 1) -> DataFrame:
        """Edges chosen by a hash of their ends: the same ones for any layout."""
        low, high = F.least("src", "dst"), F.greatest("src", "dst")
        key = F.xxhash64(F.lit(seed), *((F.col("src"), F.col("dst")) if self.directed else (low, high)))
        return self.pairs.select("src", "dst").where(F.pmod(key, F.lit(1_000_000)) < int(share * 1_000_000))

    def median_node(self) -> int:
        """The node of median out-degree; the smallest id of that degree."""
        d = self.nodes.agg(F.percentile("out_deg", F.lit(0.5))).first()[0]
        return self.nodes.where(F.col("out_deg") >= d).orderBy("out_deg", "id").first()["id"]

    def hub(self) -> int:
        return self.nodes.orderBy(F.desc("out_deg"), "id").first()["id"]

    def smallest(self) -> int:
        return self.nodes.orderBy("out_deg", "id").first()["id"]

    def register(self, prefix: str) -> None:
        self.arcs.createOrReplaceTempView(f"{prefix}_arcs")
        self.nodes.createOrReplaceTempView(f"{prefix}_nodes")


def _sorted_pairs(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs in order of (src, dst)."""
    if len(src):
        low, least = int(src.min()), int(dst.min())
        bits = (int(dst.max()) - least).bit_length()
        if (int(src.max()) - low).bit_length() + bits <= 63:
            key = (src - low) << bits | dst - least
            key.sort()
            key = key[np.append(True, key[1:] != key[:-1])]
            return (key >> bits) + low, (key & ((1 << bits) - 1)) + least
        order = np.lexsort((dst, src))
        src, dst = src[order], dst[order]
        new = np.append(True, (src[1:] != src[:-1]) | (dst[1:] != dst[:-1]))
        src, dst = src[new], dst[new]
    return src, dst


def _pack(src: np.ndarray, dst: np.ndarray) -> bytes:
    """Pairs in order as differences of neighbours in the fewest bytes, byte by byte, compressed."""
    out = [len(src).to_bytes(8, "little")]
    for column in (src, dst):
        step = np.diff(column, prepend=np.int64(0))
        step = (step << 1 ^ step >> 63).view(np.uint64)
        wide = next(w for w in (1, 2, 3, 4, 8) if w == 8 or int(step.max(initial=0)) >> 8 * w == 0)
        raw = np.ascontiguousarray(step.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :wide].T).tobytes()
        held = pa.compress(raw, "zstd", asbytes=True)
        out += [bytes([wide]), len(held).to_bytes(8, "little"), held]
    return b"".join(out)


def _unpack(run: bytes) -> tuple[np.ndarray, np.ndarray]:
    n, at, out = int.from_bytes(run[:8], "little"), 8, []
    for _ in range(2):
        wide, size = run[at], int.from_bytes(run[at + 1 : at + 9], "little")
        raw = pa.decompress(run[at + 9 : at + 9 + size], n * wide, "zstd", asbytes=True) if n else b""
        step = np.zeros((n, 8), np.uint8)
        step[:, :wide] = np.frombuffer(raw, np.uint8).reshape(wide, n).T
        step = step.view("<u8").ravel()
        out.append(np.cumsum((step >> np.uint64(1)).astype(np.int64) ^ -(step & np.uint64(1)).astype(np.int64)))
        at += 9 + size
    return out[0], out[1]


def _packed(drop_loops: bool):
    """Runs of distinct edges in order, with some of their rows and whether an edge has a null end or is a loop."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng = np.random.default_rng(0)
        parts, count, null_end = [], 0, False

        def rest() -> pa.RecordBatch:
            src, dst = (np.concatenate(x) for x in zip(*parts)) if parts else (np.zeros(0, np.int64),) * 2
            loop = src == dst
            if drop_loops:
                src, dst = src[~loop], dst[~loop]
            src, dst = _sorted_pairs(src, dst)
            some = rng.integers(0, len(src), -(-len(src) // SAMPLE_EVERY)) if len(src) else np.zeros(0, np.int64)
            return pa.RecordBatch.from_pydict({"run": [_pack(src, dst)], "sample": [np.column_stack([src[some], dst[some]]).tobytes()], "null_end": [null_end], "loop": [bool(loop.any())]})

        for batch in batches:
            if batch.column(0).null_count or batch.column(1).null_count:
                null_end = True
                continue
            parts.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            count += len(parts[-1][0])
            if count >= RUN_ARCS:
                yield rest()
                parts, count = [], 0
        if count or null_end:
            yield rest()

    return run


def _bounds(sample: np.ndarray, both: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where pieces of about ``PIECE_ARCS`` begin: (src, dst) of each but the first, and the group of each piece.

    A piece begins with a node's first arc, but a node that takes several pieces is cut; all that have a part of it are one group.
    """
    if both:
        sample = np.concatenate([sample, sample[:, ::-1]])
    sample = sample[np.lexsort((sample[:, 1], sample[:, 0]))]
    step = max(1, PIECE_ARCS // SAMPLE_EVERY)
    cut = sample[step::step]
    inner = np.append(False, cut[1:, 0] == cut[:-1, 0])[: len(cut)]
    dst = np.where(inner, cut[:, 1], np.iinfo(np.int64).min)
    return cut[:, 0], dst, np.concatenate(([0], np.cumsum(~inner)))


def _dealt(src_at: np.ndarray, dst_at: np.ndarray, group: np.ndarray, both: bool):
    """The packed parts of each run in each piece."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        clean = dst_at == np.iinfo(np.int64).min
        for batch in batches:
            for held in batch.column(0):
                src, dst = _unpack(held.as_py())
                for turned in (False, True) if both else (False,):
                    x, y = _sorted_pairs(dst, src) if turned else (src, dst)
                    at = np.searchsorted(x, src_at)
                    for i in np.flatnonzero(~clean):
                        at[i] += np.searchsorted(y[at[i] : np.searchsorted(x, src_at[i], "right")], dst_at[i])
                    at = np.concatenate(([0], at, [len(x)]))
                    has = np.flatnonzero(np.diff(at))
                    yield pa.RecordBatch.from_pydict({"grp": pa.array(group[has], pa.int64()), "piece": pa.array(has, pa.int64()), "run": pa.array([_pack(x[at[i] : at[i + 1]], y[at[i] : at[i + 1]]) for i in has], pa.binary())})

    return run


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(src, dst) in order, piece by piece."""
    parts, now = [], None

    def rest() -> Iterator[pa.RecordBatch]:
        src, dst = _sorted_pairs(*(np.concatenate(x) for x in zip(*parts)))
        for lo in range(0, len(src), BATCH_ARCS):
            yield pa.RecordBatch.from_arrays([pa.array(src[lo : lo + BATCH_ARCS]), pa.array(dst[lo : lo + BATCH_ARCS])], names=["src", "dst"])

    for batch in batches:
        for piece, held in zip(batch.column(0).to_pylist(), batch.column(1)):
            if parts and piece != now:
                yield from rest()
                parts = []
            now = piece
            parts.append(_unpack(held.as_py()))
    if parts:
        yield from rest()


def _placed(edges: DataFrame, both: bool = False, self_loops: str = "keep") -> DataFrame:
    """Distinct (src, dst, idx, out_deg), with the turned rows if ``both``: idx from 0 in order of dst.

    Edges are saved as packed runs; their parts go through one shuffle, into ranges of src.  Repeated rows go when runs are
    packed and again when arcs are numbered.
    """
    ship(edges.sparkSession)
    runs = saved(edges.select("src", "dst").mapInArrow(_packed(self_loops == "drop"), "run binary, sample binary, null_end boolean, loop boolean"))
    found = runs.select("sample", "null_end", "loop").toArrow()
    if any(found.column("null_end").to_pylist()):
        raise GraphError("an edge has a null end")
    if self_loops == "auto" and any(found.column("loop").to_pylist()):
        raise GraphError("an undirected graph has a self-loop")
    sample = np.frombuffer(b"".join(found.column("sample").to_pylist()), np.int64).reshape(-1, 2)
    src, dst, group = _bounds(sample, both)
    dealt = runs.select("run").mapInArrow(_dealt(src, dst, group, both), "grp long, piece long, run binary")
    dealt = dealt.repartition(int(group[-1]) + 1, "grp").sortWithinPartitions("piece").select("piece", "run")
    return dealt.mapInArrow(lambda batches: _numbered(_merged(batches)), "src long, dst long, idx long, out_deg long")


def _numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by (src, dst).  The last node's arcs are held until its next one comes, those of a hub in a file."""
    names = ["src", "dst", "idx", "out_deg"]
    held, in_file, now, last = [], 0, None, None
    with tempfile.TemporaryFile() as file:

        def rest() -> Iterator[pa.RecordBatch]:
            """The arcs of the node that is held."""
            total, done = in_file + sum(map(len, held)), 0
            file.seek(0)
            while done < total:
                dst = np.fromfile(file, np.int64, min(HELD_ARCS, in_file - done)) if done < in_file else np.concatenate(held)
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (np.full(len(dst), now), dst, np.arange(done, done + len(dst)), np.full(len(dst), total))], names=names)
                done += len(dst)

        for batch in batches:
            src, dst = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            if not len(src):
                continue
            new = np.append(now is None or src[0] != now or dst[0] != last, (src[1:] != src[:-1]) | (dst[1:] != dst[:-1]))
            last = dst[-1]
            src, dst = src[new], dst[new]
            if not len(src):
                continue
            cuts = np.flatnonzero(np.diff(src)) + 1
            begin = np.concatenate(([0], cuts))
            if src[0] == now:
                held.append(dst[: cuts[0] if len(cuts) else len(dst)])
            if src[0] != now or len(cuts):
                if now is not None:
                    yield from rest()
                # whole nodes of this batch, then the one that may go on
                lo, hi = (begin[1] if src[0] == now else 0), begin[-1]
                if lo < hi:
                    inner = begin[(begin >= lo) & (begin < hi)]
                    deg = np.diff(np.append(inner, hi))
                    start, out_deg = np.repeat(inner, deg), np.repeat(deg, deg)
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in (src[lo:hi], dst[lo:hi], np.arange(lo, hi) - start, out_deg)], names=names)
                held, in_file, now = [dst[hi:]], 0, src[-1]
                file.seek(0)
                file.truncate()
            if sum(map(len, held)) > HELD_ARCS:
                file.seek(0, os.SEEK_END)
                np.concatenate(held).tofile(file)
                file.flush()
                in_file, held = in_file + sum(map(len, held)), []
        if now is not None:
            yield from rest()
