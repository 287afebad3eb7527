"""Adjacency lists from raw edges as packed numbers: one shuffle of eight bytes an edge row, each range of nodes sorted in one task."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle

#: Raw edges that a task codes at a time, and edge rows of a range of nodes; a hub may make its range longer.
CODE_ROWS = 1 << 20
RANGE_ROWS = 1 << 20

TABLE = "hash binary, node binary, ends binary"
CODES = "range int, codes binary"
LISTS = "range int, first long, held long, most int, deg binary, nbr binary"


def by_value() -> None:
    cloudpickle.register_pickle_by_value(sys.modules[__name__])


def table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(hash, node, ends) of many keys in one row."""
    held = [[c.to_numpy(zero_copy_only=False) for c in batch.columns] for batch in batches]
    if held:
        columns = [np.concatenate(x).astype(kind).tobytes() for x, kind in zip(zip(*held), (np.int64, np.int32, np.int64))]
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.binary()) for x in columns], ["hash", "node", "ends"])


def opened(rows) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes in order, their nodes, ends by node) from the rows of `table`."""
    hashes, nodes, ends = (
        np.concatenate([np.frombuffer(r[c], kind) for r in rows]) for c, kind in (("hash", np.int64), ("node", np.int32), ("ends", np.int64))
    )
    order, by_node = np.argsort(hashes), np.empty(len(nodes), np.int64)
    by_node[nodes] = ends
    return hashes[order], nodes[order], by_node


def ranges(ends: np.ndarray) -> np.ndarray:
    """First nodes of ranges that hold about RANGE_ROWS ends each."""
    count = -(-int(ends.sum()) // RANGE_ROWS)
    marks = np.arange(1, count) * RANGE_ROWS
    return np.unique(np.concatenate(([0], np.searchsorted(np.cumsum(ends), marks))))


def _distinct(codes: np.ndarray) -> np.ndarray:
    codes.sort()
    return codes[np.concatenate((np.ones(min(len(codes), 1), bool), codes[1:] != codes[:-1]))]


def coded(shared, firsts: np.ndarray):
    """Hashes of both ends to edges of both directions as src * 2^32 + dst, by the range of src."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, nodes = shared.value

        def part(held: list) -> pa.RecordBatch:
            a, b = (nodes[np.searchsorted(hashes, np.concatenate(x))].astype(np.int64) for x in zip(*held))
            codes = _distinct(np.concatenate((a << 32 | b, b << 32 | a)))
            at = np.append(np.searchsorted(codes, firsts << 32), len(codes))
            some = np.flatnonzero(np.diff(at))
            return pa.RecordBatch.from_arrays(
                [pa.array(some, pa.int32()), pa.array([codes[at[i] : at[i + 1]].tobytes() for i in some], pa.binary())], ["range", "codes"]
            )

        held, rows = [], 0
        for batch in batches:
            held.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
            rows += batch.num_rows
            if rows >= CODE_ROWS:
                yield part(held)
                held, rows = [], 0
        if rows:
            yield part(held)

    return run


def listed(firsts: np.ndarray, n: int):
    """Codes of whole ranges to LISTS rows: degrees, and neighbours in their order."""
    lasts = np.append(firsts[1:], n)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for batch in batches:
            for i, codes in zip(batch.column("range").to_pylist(), batch.column("codes")):
                held.setdefault(i, []).append(np.frombuffer(codes.as_py(), np.int64))
        for i in sorted(held):
            codes = _distinct(np.concatenate(held.pop(i)))
            deg = np.bincount((codes >> 32) - firsts[i], minlength=lasts[i] - firsts[i]).astype(np.int32)
            row = i, int(firsts[i]), len(codes), int(deg.max()), deg.tobytes(), codes.astype(np.uint32).view(np.int32).tobytes()
            kinds = pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.binary()
            yield pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip(row, kinds)], ["range", "first", "held", "most", "deg", "nbr"])

    return run


def degrees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, deg) of the rows of (first, deg)."""
    for batch in batches:
        for first, deg in zip(batch.column("first").to_pylist(), batch.column("deg")):
            deg = np.frombuffer(deg.as_py(), np.int32).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(first, first + len(deg))), pa.array(deg)], ["node", "deg"])


def edges(shared=None):
    """(src, dst) of the lists in their order; with all degrees shared also (pos, src_deg, dst_deg)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, deg, nbr in zip(batch.column("first").to_pylist(), batch.column("deg"), batch.column("nbr")):
                deg, nbr = np.frombuffer(deg.as_py(), np.int32), np.frombuffer(nbr.as_py(), np.int32)
                ends = np.cumsum(deg, dtype=np.int64)
                for a in range(0, len(nbr), 1 << 16):
                    place = np.arange(a, min(a + (1 << 16), len(nbr)))
                    src, dst = np.searchsorted(ends, place, "right"), nbr[place].astype(np.int64)
                    out = {"src": src + first, "dst": dst}
                    if shared is not None:
                        out |= {"pos": (place - ends[src] + deg[src] + 1).astype(np.int32), "src_deg": deg[src].astype(np.int64), "dst_deg": shared.value[dst].astype(np.int64)}
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in out.values()], list(out))

    return run
