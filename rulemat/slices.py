"""Array kernels over slices of an edge table; imported by workers, so it stays small."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Edges that a task holds at once; a task with more makes several slices of them.
SLICE = 1_000_000


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    held: list[pa.RecordBatch] = []
    rows = 0
    for b in batches:
        while b.num_rows:
            part = b.slice(0, SLICE - rows)
            b = b.slice(part.num_rows)
            held.append(part)
            rows += part.num_rows
            if rows == SLICE:
                yield pa.Table.from_batches(held)
                held, rows = [], 0
    if held:
        yield pa.Table.from_batches(held)


def _coded(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The nodes of a slice in order, and the places of both ends of its edges among them."""
    ends = [t.column(c).to_numpy() for c in ("a", "b")]
    nodes, code = np.unique(np.concatenate(ends), return_inverse=True)
    return nodes, code[: t.num_rows], code[t.num_rows :]


def _batch(t: pa.Table, nodes: np.ndarray, **columns: np.ndarray) -> pa.RecordBatch:
    kind = t.schema.field("a").type
    return pa.RecordBatch.from_pydict({k: pa.array(v) if k == "left" else pa.array(nodes[v], kind) for k, v in columns.items()})


def stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, root): the least node that each node reaches by the edges (a, b) of its slice."""
    for t in _slices(batches):
        nodes, u, v = _coded(t)
        root = np.arange(len(nodes))
        while True:
            x, y = root[u], root[v]
            apart = x != y
            if not apart.any():
                break
            u, v, x, y = u[apart], v[apart], x[apart], y[apart]
            np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))  # roots hang below lesser ones only
            while not np.array_equal(up := root[root], root):
                root = up
        yield _batch(t, nodes, node=np.arange(len(nodes)), root=root)


def tails(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, last, left): where the edges (a, b, left) of a slice lead from each a that has one
    edge at most, and over how many steps; -1 steps on a circle."""
    for t in _slices(batches):
        nodes, u, v = _coded(t)
        at, left = np.arange(len(nodes)), np.zeros(len(nodes), "int64")
        at[u], left[u] = v, t.column("left").to_numpy()
        moving, rounds = left > 0, 0
        while moving.any() and rounds <= len(nodes).bit_length():
            more = left[at]
            moving, left, at, rounds = more > 0, left + more, at[at], rounds + 1
        left[moving] = -1
        yield _batch(t, nodes, node=u, last=at[u], left=left[u])


def counts_before(t: pa.Table) -> pa.Table:
    """(node, result): for each row of a chain that asks, the values of all rows of lesser key,
    counted.  Nulls count nothing; nodes without any such row have no result."""
    asks, node, valid, _ = _along(t)
    rows, n = np.cumsum(~asks), np.cumsum(valid)
    give = asks & (rows > 0)
    return _results(t, node[give], pa.array(n[give]))


def medians_before(t: pa.Table) -> pa.Table:
    """The same, with the median of the values: two heaps meet in the middle of what was seen."""
    asks, node, valid, values = _along(t)
    place = np.empty(len(values), "int64")
    place[np.argsort(values, kind="stable")] = np.arange(len(values))  # NaN last, as in Spark
    ordered = np.sort(values)
    low: list[int] = []  # places, negated
    high: list[int] = []
    nodes, out, rows = [], [], 0
    for ask, k, there, at in zip(asks.tolist(), node.tolist(), valid.tolist(), place.tolist(), strict=True):
        if not ask:
            rows += 1
            if there:
                if len(low) > len(high):
                    heapq.heappush(high, -heapq.heappushpop(low, -at))
                else:
                    heapq.heappush(low, -heapq.heappushpop(high, at))
        elif rows:
            nodes.append(k)
            if not low:
                out.append(None)
            elif len(low) > len(high):
                out.append(float(ordered[-low[0]]))
            else:
                a, b = ordered[-low[0]], ordered[high[0]]
                out.append(float(a if a == b else 0.5 * a + 0.5 * b))
    return _results(t, np.array(nodes, "int64"), pa.array(out, pa.float64()))


def _along(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Rows of a chain in the order of their keys, those that ask before others of their key:
    whether they ask, their place in the table, whether they have a value, and the value."""
    asks, value = t.column("asks").to_numpy(), t.column("value")
    order = np.lexsort((~asks, t.column("key").to_numpy()))
    valid = value.is_valid().to_numpy()
    return asks[order], order, (valid & ~asks)[order], value.fill_null(0.0).to_numpy()[order]


def _results(t: pa.Table, at: np.ndarray, result: pa.Array) -> pa.Table:
    return pa.table({"node": t.column("node").take(pa.array(at)), "result": result})
