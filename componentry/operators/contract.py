"""Local pre-contraction: each partition replaces its edges by a spanning forest of them.

Exact for components, as the forest joins what the edges join. With weights a minimum spanning forest
stays, which is exact for single linkage (no heaviest edge of a cycle is ever needed). Without weights each part of a
block may as well become a star around its least id, which joins the same ids by paths of two hops.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame


class DisjointSets:
    """Union-find over hashable ids with path halving; the least id is the root."""

    def __init__(self) -> None:
        self.up: dict = {}

    def find(self, x):
        up = self.up
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a, b) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        if b < a:
            a, b = b, a
        self.up[b] = a
        return True


def _key(x):
    """An id that can be looked up and compared: fields of a struct in order."""
    return tuple(map(_key, x.values())) if isinstance(x, dict) else x


def _numbered(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """The ids in order, and the edges between their places."""
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    return ids, list(zip(ends[: len(src)].tolist(), ends[len(src) :].tolist(), strict=True))


def spanning(src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Whether each edge, in this order, joins two parts that were apart."""
    ids, edges = _numbered(src, dst)
    return _joins(len(ids), edges)[0]


def _joins(n: int, edges: list[tuple[int, int]]) -> tuple[np.ndarray, list[int]]:
    """(whether each edge joins two parts, the least of its part for each of ``n``), by union-find over small numbers."""
    up = list(range(n))
    keep = np.zeros(len(edges), bool)
    for k, (a, b) in enumerate(edges):
        while up[a] != a:
            up[a] = a = up[up[a]]
        while up[b] != b:
            up[b] = b = up[up[b]]
        if a != b:
            keep[k] = True
            if a < b:
                up[b] = a
            else:
                up[a] = b
    for i in range(n):  # roots are the least of their parts, so each is settled before what hangs on it
        up[i] = up[up[i]]
    return keep, up


def star_edges(edges: DataFrame, batch_rows: int = 200_000) -> DataFrame:
    """Each block of at most ``batch_rows`` edges as stars: every id of a part to the least of it."""

    def star(table: pa.Table) -> pa.Table:
        if pa.types.is_integer(table["src"].type) and not table["src"].null_count and not table["dst"].null_count:
            ids, own = _numbered(table["src"].to_numpy(), table["dst"].to_numpy())
            root = np.array(_joins(len(ids), own)[1], np.int64)
            hangs = root != np.arange(len(ids))
            return pa.table({"src": ids[root[hangs]], "dst": ids[hangs]}, schema=table.schema)
        sets, named = DisjointSets(), {}
        for a, b in zip(table["src"].to_pylist(), table["dst"].to_pylist(), strict=True):
            named[_key(a)], named[_key(b)] = a, b
            sets.join(_key(a), _key(b))
        rows = [{"src": named[sets.find(x)], "dst": named[x]} for x in list(sets.up) if sets.find(x) != x]
        return pa.Table.from_pylist(rows, schema=table.schema)

    return _by_block(edges.select("src", "dst"), batch_rows, star)


def _by_block(edges: DataFrame, batch_rows: int, shrink: Callable[[pa.Table], pa.Table]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= batch_rows:
                yield from shrink(pa.Table.from_batches(held)).to_batches()
                held, rows = [], 0
        if rows:
            yield from shrink(pa.Table.from_batches(held)).to_batches()

    return edges.mapInArrow(run, edges.schema)


def forest_edges(edges: DataFrame, batch_rows: int = 200_000) -> DataFrame:
    """Spanning forest of each block of at most ``batch_rows`` edges; memory is bounded by the block."""
    weighted = "w" in edges.columns

    def forest(table: pa.Table) -> pa.Table:
        if weighted:
            table = table.sort_by([("w", "ascending"), ("src", "ascending"), ("dst", "ascending")])
        if pa.types.is_integer(table["src"].type) and not table["src"].null_count and not table["dst"].null_count:
            keep = spanning(table["src"].to_numpy(), table["dst"].to_numpy())
        else:
            sets = DisjointSets()
            keep = [sets.join(_key(a), _key(b)) for a, b in zip(table["src"].to_pylist(), table["dst"].to_pylist(), strict=True)]
        return table.filter(pa.array(keep, pa.bool_()))

    return _by_block(edges.select("src", "dst", *(["w"] if weighted else [])), batch_rows, forest)
