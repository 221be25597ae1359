"""Union-find in one task for what is left when the graph is small, and in each input task.

Edges are streamed: a chunk joins the spanning forest of what came before, so memory follows
the vertices (two longs each, and a few times that while a chunk is joined), not the edges.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame

CHUNK = 1 << 20


def least_labels(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vertices of the pairs, in order, and the place of each one's root, the lowest vertex of its component.

    Roots of open pairs are hooked to lower ones, then all pointers are halved until they rest.
    """
    ids, flat = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = flat[: len(a)], flat[len(a) :]
    low = np.arange(len(ids))
    while len(x):
        x, y = low[x], low[y]
        open_ = x != y
        x, y = x[open_], y[open_]
        np.minimum.at(low, np.maximum(x, y), np.minimum(x, y))
        while (low != (nxt := low[low])).any():
            low = nxt
    return ids, low


def _stars(batches) -> tuple[np.ndarray, np.ndarray]:
    """Vertices and roots (lowest vertices) of the edges."""
    v, root = np.zeros(0, np.int64), np.zeros(0, np.int64)
    held: list[tuple[np.ndarray, np.ndarray]] = []
    n = 0

    def join():
        ids, low = least_labels(np.concatenate([v, *[h[0] for h in held]]), np.concatenate([root, *[h[1] for h in held]]))
        return ids, ids[low]

    for b in batches:
        if b.num_rows:
            held.append((b.column("src").to_numpy(), b.column("dst").to_numpy()))
            n += b.num_rows
        # joining costs as much as the forest, so chunks grow with it
        if n >= max(CHUNK, len(v)):
            v, root = join()
            held, n = [], 0
    return join() if held else (v, root)


def _spanning(batches, emit_edges: bool) -> Iterator:
    import pyarrow as pa

    v, root = _stars(batches)
    names = ["v", "node"]
    if emit_edges:
        keep = v != root
        v, root, names = root[keep], v[keep], ["src", "dst"]
    for i in range(0, len(v), 1 << 16):
        yield pa.RecordBatch.from_arrays([pa.array(v[i : i + (1 << 16)]), pa.array(root[i : i + (1 << 16)])], names=names)


def union_find(edges: DataFrame) -> DataFrame:
    """``v, node`` with node the lowest vertex: edges are streamed, memory follows the vertices. One task."""
    return edges.select("src", "dst").coalesce(1).mapInArrow(lambda it: _spanning(it, False), "v long, node long")


def local_forest(edges: DataFrame) -> DataFrame:
    """A spanning forest (stars) of the edges of each input task: same components, at most vertices-per-task edges."""
    return edges.select("src", "dst").mapInArrow(lambda it: _spanning(it, True), "src long, dst long")
