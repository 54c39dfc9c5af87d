"""In-task numpy kernels over a broadcast adjacency, for graphs under the size check.

They do the same synchronous rounds and use the same random draws as the shuffle engines, so both
give the same numbers (up to the order of float sums).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from ..functions import prng

#: Arcs that a kernel goes through at once.
CHUNK_ARCS = 4_000_000


def run_walks(csr, at: np.ndarray, trial: np.ndarray, walk: np.ndarray, seed: int, alpha: float, rng: str) -> tuple[np.ndarray, int]:
    """End nodes of stopping walks, and the number of moves made."""
    wide = rng == "wide"
    key = (prng.wide_key if wide else prng.walk_key)(seed, trial, walk)
    draw = prng.wide_draw if wide else prng.draw
    limit, out_deg = prng.stop_limit(alpha), csr.out_deg
    at, live, step, moves = at.copy(), np.arange(len(at)), 0, 0
    while len(live):
        live = live[draw(key[live], step, 0) >= limit]
        here = at[live]
        at[live] = csr.out_to[csr.out_at[here] + draw(key[live], step, 1) % out_deg[here]]
        moves += len(live)
        step += 1
    return at, moves


def pick_starts(starts, trial: np.ndarray, walk: np.ndarray, seed: int, rng: str) -> np.ndarray:
    """Start places of walks: a fixed place, or a draw from an alias table (accept, alias)."""
    if isinstance(starts, (int, np.integer)):
        return np.full(len(walk), starts, np.int64)
    accept, alias = starts
    wide = rng == "wide"
    key = (prng.wide_key if wide else prng.walk_key)(seed, trial, walk)
    draw = prng.wide_draw if wide else prng.draw
    slot = draw(key, 1_000_003, 0) % len(accept)
    return np.where(draw(key, 1_000_003, 1) < accept[slot] * prng.P, slot, alias[slot])


def _ranges(begin: np.ndarray, counts: np.ndarray) -> np.ndarray:
    total = int(counts.sum())
    shift = np.repeat(begin - np.concatenate(([0], np.cumsum(counts)[:-1])), counts)
    return np.arange(total) + shift


def reverse_push(csr, target: int, theta: float, alpha: float, budget: float = np.inf, state: tuple | None = None, max_rounds: int = 20_000):
    """(reserve, residue, cost, rounds, within budget) of synchronous reverse pushes toward one place."""
    n = len(csr.ids)
    if state is None:
        reserve, residue = np.zeros(n), np.zeros(n)
        residue[target] = 1.0
    else:
        reserve, residue = state
    in_at, out_at, cost, rounds = csr.in_at, csr.out_at, 0, 0
    hot = np.flatnonzero(residue > theta)
    while True:
        if not len(hot):
            return reserve, residue, cost, rounds, True
        counts = in_at[hot + 1] - in_at[hot]
        if cost + counts.sum() > budget:
            return reserve, residue, cost, rounds, False
        if rounds >= max_rounds:
            raise RuntimeError("a push did not end within max_rounds")
        cost += int(counts.sum())
        rounds += 1
        r = residue[hot]
        reserve[hot] += alpha * r
        residue[hot] = 0
        src = csr.in_from[_ranges(in_at[hot], counts)]
        # only nodes that got something can be hot in the next round
        near, place = np.unique(src, return_inverse=True)
        residue[near] += np.bincount(place, np.repeat((1 - alpha) * r, counts) / (out_at[src + 1] - out_at[src]), len(near))
        hot = near[residue[near] > theta]


def forward_push(csr, start: np.ndarray, rmax: float, alpha: float, max_rounds: int = 20_000):
    """(reserve, residue, cost, rounds) of synchronous forward pushes; ``start`` is the initial residue."""
    n = len(csr.ids)
    reserve, residue, out_deg, cost, rounds = np.zeros(n), start.astype(float), csr.out_deg, 0, 0
    while True:
        hot = np.flatnonzero(residue > rmax * out_deg)
        if not len(hot):
            return reserve, residue, cost, rounds
        if rounds >= max_rounds:
            raise RuntimeError("a push did not end within max_rounds")
        counts = out_deg[hot]
        cost += int(counts.sum())
        rounds += 1
        r = residue[hot]
        reserve[hot] += alpha * r
        residue[hot] = 0
        residue += np.bincount(csr.out_to[_ranges(csr.out_at[hot], counts)], np.repeat((1 - alpha) * r / counts, counts), n)


def power(csr, start: np.ndarray, alpha: float, rounds: int) -> np.ndarray:
    """Truncated series of the walk's end distribution."""
    n, out_deg = len(csr.ids), csr.out_deg
    mass, total = start.astype(float), np.zeros(n)
    for _ in range(rounds + 1):
        total += alpha * mass
        share, mass = mass / out_deg, np.zeros(n)
        for lo, hi in _chunks(csr.out_at):
            mass += np.bincount(csr.out_to[csr.out_at[lo] : csr.out_at[hi]], np.repeat(share[lo:hi], out_deg[lo:hi]), n)
        mass *= 1 - alpha
    return total


def _chunks(at: np.ndarray) -> list[tuple[int, int]]:
    """Ranges of places with about ``CHUNK_ARCS`` arcs each; a place of more stands alone."""
    cuts = np.unique(np.searchsorted(at, np.arange(0, at[-1] + CHUNK_ARCS, CHUNK_ARCS))).clip(0, len(at) - 1)
    cuts = np.unique(np.concatenate(([0], cuts, [len(at) - 1])))
    return list(zip(cuts[:-1], cuts[1:]))


def reverse_power(csr, target: int, alpha: float, rounds: int) -> np.ndarray:
    """Scores of all sources toward one place."""
    n, out_deg, in_deg = len(csr.ids), csr.out_deg, csr.in_deg
    mass, total = np.zeros(n), np.zeros(n)
    mass[target] = 1.0
    for _ in range(rounds + 1):
        total += alpha * mass
        before, mass = mass, np.zeros(n)
        for lo, hi in _chunks(csr.in_at):
            src = csr.in_from[csr.in_at[lo] : csr.in_at[hi]]
            mass += np.bincount(src, np.repeat(before[lo:hi], in_deg[lo:hi]), n)
        mass *= (1 - alpha) / out_deg
    return total


def sparse_rows(names: list[str], kinds: list[pa.DataType], columns: list[np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)


def each_row(function):
    """A mapInArrow function from one that gives batches for a dict of a row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                yield from function(row)

    return run
