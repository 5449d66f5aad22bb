"""Exact top-k by inner product as a Voronoi join.

Vectors become integers, floor(scale * x). With M the largest length of a vector, a candidate x is lifted to
(x, sqrt(M^2 - |x|^2)) and a query q to (q, 0): then |q - x|^2 = |q|^2 + M^2 - 2 q.x, so the largest inner products
are the nearest neighbours, and the triangle inequality bounds them.

1. Candidates and queries are both grouped by their nearest pivot. Pivots are vectors of a hashed order, about the root
   of the number of rows and ``PIVOTS`` at most: a documented sample that affects speed alone.
2. A candidate cell's summary is its rows, radius and k + 1 least pivot distances; from the summaries each query
   gets a bound on the distance of its k-th neighbour. A query cell's summary is its queries, its radius and the
   largest of their bounds.
3. Query cells are joined into groups along a chain of near pivots; of several group sizes the one is taken that,
   by the summaries, sends the fewest rows. For a group and a candidate cell the summaries give a ring of pivot
   distances outside which no candidate can be within any bound: only candidates in the ring are replicated to the group.
   A query is sent to those candidate cells that hold something within its own bound.
4. Candidate cells are joined, or cut, into bins of ``SHARD`` rows, groups cut into blocks of ``BLOCK`` queries, so
   a task's memory follows neither a hot cell nor the number of queries. Each block meets each bin once, exactly,
   and the best k of all bins are merged.

Vectors that are null, hold null or non-finite components, or have no id take no part; an empty table gives no rows.
Components past the 64-bit range saturate, and so do scores. A shorter vector counts as ending in zeros. Repeated rows
are candidates of each other: only a query's own row is left out. Ties go to smaller ids. Only the two columns named are
read, so others never clash.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.plans.storage import cut

PIVOTS = 1024
SHARD = 32_768
BLOCK = 32_768
SLACK = 1e-6
_ROWS = 256  # queries whose distances and scores are held at once

_FOUND = T.StructType([T.StructField(n, T.LongType()) for n in ("query_row", "query_id", "vec_id", "score")])


def integer_vectors(df: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding", scale: int = 1024) -> DataFrame:
    """(row, vec_id, v) of the vectors that take part, v as integers."""
    x = F.col(embedding)
    bad = F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c.cast("double")) == F.lit(float("inf"))))
    kept = df.where(F.col(vec_id).isNotNull() & x.isNotNull() & ~F.coalesce(bad, F.lit(True)))
    return kept.select(F.monotonically_increasing_id().alias("row"), F.col(vec_id).cast("long").alias("vec_id"), F.transform(x, lambda c: F.floor(c.cast("double") * scale)).alias("v"))


def _matrix(column: pa.ChunkedArray | pa.Array, width: int) -> np.ndarray:
    rows = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.diff(rows.offsets.to_numpy())
    flat = rows.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    if len(sizes) and (sizes == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(sizes), width), np.int64)
    at = np.repeat(np.arange(len(sizes)), sizes)
    place = np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    out[at, place] = flat
    return out


def _products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact a @ b.T: in floating point where every sum is exact in it, else in Python's integers, saturated."""
    most = float(np.abs(a.astype(float)).max(initial=0)) * float(np.abs(b.astype(float)).max(initial=0)) * max(1, a.shape[1])
    if most < 2.0**53:
        return (a.astype(float) @ b.astype(float).T).astype(np.int64)
    exact = a.astype(object) @ b.astype(object).T
    return np.clip(exact, -(2**63), 2**63 - 1).astype(np.int64)


def _pivot_distances(x: np.ndarray, pivots: np.ndarray, longest: float, lifted: bool) -> np.ndarray:
    """Distances of candidates (lifted) or queries to the lifted pivots."""
    f, p = x.astype(float), pivots.astype(float)
    square = (f * f).sum(1)[:, None]
    d = square + longest**2 - 2 * f @ p.T
    if lifted:
        own = np.sqrt(np.maximum(0, longest**2 - square))
        d = 2 * longest**2 - 2 * f @ p.T - 2 * own * np.sqrt(np.maximum(0, longest**2 - (p * p).sum(1)))[None, :]
    return np.sqrt(np.maximum(0, d))


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the ``k`` best of a row of scores, ties to smaller ids."""
    if len(scores) > 4 * k:
        least = np.partition(scores, len(scores) - k)[len(scores) - k]
        at = np.flatnonzero(scores >= least)
    else:
        at = np.arange(len(scores))
    return at[np.lexsort((ids[at], -scores[at].astype(float) if scores.dtype != np.int64 else np.negative(np.maximum(scores[at], -(2**63) + 1))))][:k]


def pivot_chain(between: np.ndarray) -> np.ndarray:
    """The pivots in an order in which each is followed by the nearest that is left."""
    left, order = np.ones(len(between), bool), [0]
    left[0] = False
    while left.any():
        d = np.where(left, between[order[-1]], np.inf)
        order.append(int(d.argmin()))
        left[order[-1]] = False
    return np.array(order)


def _runs(weights: np.ndarray, most: int) -> np.ndarray:
    """Number of the run of each place, where runs of neighbours weigh up to ``most`` (one place may weigh more)."""
    out, run, total = np.zeros(len(weights), np.int64), 0, 0
    for i, w in enumerate(weights.tolist()):
        if total and total + w > most:
            run, total = run + 1, 0
        out[i], total = run, total + w
    return out


@dataclass
class Tiling:
    """Query cells by group, and the ring of each group and candidate cell."""

    group: np.ndarray  # of each query cell
    blocks: np.ndarray  # of each group
    low: np.ndarray  # (group, candidate cell): least and greatest pivot distance that can matter
    high: np.ndarray
    facts: dict = field(default_factory=dict)


def cell_bins(chain: np.ndarray, rows: np.ndarray, shard: int) -> tuple[np.ndarray, np.ndarray]:
    """(first bin, number of bins) of each candidate cell of so many ``rows``: neighbours on the chain share a bin, a hot cell has several."""
    bins = np.maximum(1, -(-rows // shard))
    run = np.empty(len(chain), np.int64)
    run[chain] = _runs(rows[chain], shard)
    size = np.zeros(run.max() + 1, np.int64)
    np.maximum.at(size, run, bins)
    return (np.cumsum(size) - size)[run], bins


def tiling(chain: np.ndarray, between: np.ndarray, rows: np.ndarray, radius: np.ndarray, bins: np.ndarray, asked: np.ndarray, reach: np.ndarray, bound: np.ndarray, block: int, slack: float) -> Tiling:
    """The tiling that sends the fewest rows by the summaries.

    ``between``: pivot distances; ``rows``, ``radius``, ``bins``: of candidate cells; ``asked``, ``reach``, ``bound``: number
    of queries of query cells, their greatest distance to the pivot and their greatest bound.
    """
    low, high = between - (reach + bound)[:, None] - slack, between + (reach + bound)[:, None] + slack
    may = (rows > 0)[None] & (asked > 0)[:, None] & (low <= radius[None])
    best = None
    most = block
    while True:
        group = np.empty(len(chain), np.int64)
        group[chain] = _runs(asked[chain], most)
        n = group.max() + 1
        total = np.bincount(group, asked, n)
        blocks = np.maximum(1, -(-total // block)).astype(np.int64)
        need = np.zeros((n, len(rows)), bool)
        np.logical_or.at(need, group, may)
        sent = float((need * (rows * 1.0)[None] * blocks[:, None]).sum() + (need * bins[None] * total[:, None]).sum())
        if best is None or sent < best[0]:
            low_g, high_g = np.full(need.shape, np.inf), np.full(need.shape, -np.inf)
            np.minimum.at(low_g, group, np.where(may, low, np.inf))
            np.maximum.at(high_g, group, np.where(may, high, -np.inf))
            best = (sent, Tiling(group, blocks, low_g, high_g, {"groups": int((total > 0).sum()), "blocks": int(blocks[total > 0].sum())}))
        if most <= 1 or n >= (asked > 0).sum():
            return best[1]
        most = min(most, int(total.max())) // 2


def voronoi_tiles(vectors: DataFrame, queries: DataFrame, k: int, pivots: int = PIVOTS, shard: int = SHARD, block: int = BLOCK) -> tuple[DataFrame, DataFrame, int, dict]:
    """(data, asked, width, facts): candidates and queries with the tile (group, block, bin) where they meet, for ``vectors`` (a cut) and ``queries``, both (row, vec_id, v)."""
    spark = vectors.sparkSession
    square = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x)
    sums = vectors.agg(F.max(F.size("v")).alias("w"), F.max(square).alias("m"), F.count(F.lit(1)).alias("n")).first()
    width, longest, n = max(1, sums["w"] or 0), float(sums["m"] or 0) ** 0.5, sums["n"]
    pivots = min(pivots, max(16, math.isqrt(n)))
    shard = min(shard, max(1024, n // 64))
    slack = SLACK * max(1.0, longest)
    chosen = vectors.orderBy(F.xxhash64("vec_id"), "row").limit(pivots).select("v").toArrow()
    centres = _matrix(chosen["v"], width) if n else np.zeros((1, width), np.int64)
    cells = len(centres)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d = _pivot_distances(_matrix(batch["v"], width), centres, longest, lifted=True)
            cell = d.argmin(1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cell.astype(np.int32)), pa.array(d[np.arange(len(cell)), cell])], names=[*batch.schema.names, "cell", "far"])

    celled = cut(vectors.mapInArrow(assign, T.StructType([*vectors.schema.fields, T.StructField("cell", T.IntegerType()), T.StructField("far", T.DoubleType())])), "cells")
    near = celled.withColumn("r", F.row_number().over(Window.partitionBy("cell").orderBy("far"))).where(F.col("r") <= k + 1).groupBy("cell").agg(F.sort_array(F.collect_list("far")).alias("near"))
    summary = celled.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.max("far").alias("radius")).join(near, "cell").collect()  # a row for each pivot
    radius, rows, least = np.full(cells, -np.inf), np.zeros(cells, np.int64), np.full((cells, k + 1), np.inf)
    for c in summary:
        radius[c["cell"]], rows[c["cell"]] = c["radius"], c["n"]
        least[c["cell"], : len(c["near"])] = c["near"]

    between = _pivot_distances(centres, centres, longest, lifted=True)
    chain = pivot_chain(between)
    first_bin, bins = cell_bins(chain, rows, shard)
    own_bins = [np.arange(a, a + b, dtype=np.int32) for a, b in zip(first_bin, bins, strict=True)]

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A query's cell, its distance, its bound, and the bins of the candidate cells that may hold something within it."""
        for batch in batches:
            for at in range(0, batch.num_rows, _ROWS):
                part = batch.slice(at, _ROWS)
                d = _pivot_distances(_matrix(part["v"], width), centres, longest, lifted=False)
                upper = (d[:, :, None] + least[None]).reshape(len(d), -1)
                bound = np.partition(upper, k, axis=1)[:, k] if upper.shape[1] > k else np.full(len(d), np.inf)
                need = (d - radius[None] <= bound[:, None] + slack) & (rows > 0)[None]
                cell = d.argmin(1)
                met = [np.unique(np.concatenate([own_bins[j] for j in np.flatnonzero(x)])) if x.any() else np.zeros(0, np.int32) for x in need]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(cell.astype(np.int32)), pa.array(d[np.arange(len(cell)), cell]), pa.array(bound), pa.array(met, pa.list_(pa.int32()))], names=[*part.schema.names, "home", "reach", "bound", "bins"])

    own = queries.select("row", "vec_id", "v")
    judged = cut(own.mapInArrow(judge, T.StructType([*own.schema.fields, T.StructField("home", T.IntegerType()), T.StructField("reach", T.DoubleType()), T.StructField("bound", T.DoubleType()), T.StructField("bins", T.ArrayType(T.IntegerType()))])), "queries")
    asked, reach, bound = np.zeros(cells, np.int64), np.zeros(cells), np.zeros(cells)
    for c in judged.groupBy("home").agg(F.count(F.lit(1)).alias("n"), F.max("reach").alias("reach"), F.max("bound").alias("bound")).collect():  # a row for each pivot
        asked[c["home"]], reach[c["home"]], bound[c["home"]] = c["n"], c["reach"], c["bound"]
    tiles = tiling(chain, between, rows, radius, bins, asked, reach, bound, block, slack)

    # a row for each pivot's candidate cell: its bins, and the ring of each group that needs it
    rings = [(j, int(first_bin[j]), int(bins[j]), [(int(g), int(tiles.blocks[g]), float(tiles.low[g, j]), float(tiles.high[g, j])) for g in np.flatnonzero(tiles.low[:, j] <= tiles.high[:, j])]) for j in range(cells)]
    book = spark.createDataFrame(rings, "cell int, first_bin int, n_bins int, rings array<struct<g: int, blocks: int, low: double, high: double>>")
    inside = F.filter("rings", lambda x: (F.col("far") >= x["low"]) & (F.col("far") <= x["high"]))
    bin_ = (F.col("first_bin") + F.pmod(F.xxhash64("row"), F.col("n_bins")).cast("int")).alias("bin")
    data = celled.join(F.broadcast(book), "cell").select("row", "vec_id", "v", bin_, F.explode(inside).alias("x"))
    data = data.select("row", "vec_id", "v", "bin", F.col("x.g").alias("g"), F.explode(F.sequence(F.lit(0), F.col("x.blocks") - 1)).alias("block"))

    homes = spark.createDataFrame([(j, int(g), int(tiles.blocks[g])) for j, g in enumerate(tiles.group)], "home int, g int, blocks int")
    block_ = F.pmod(F.xxhash64("row"), F.col("blocks")).cast("int").alias("block")
    sent = judged.join(F.broadcast(homes), "home").select("row", "vec_id", "v", "g", block_, F.explode("bins").alias("bin"))
    return data, sent, width, tiles.facts


def knn_join(vectors: DataFrame, queries: DataFrame, k: int = 10, pivots: int = PIVOTS, shard: int = SHARD, block: int = BLOCK) -> DataFrame:
    """(query_row, query_id, rank, vec_id, score) of each row of ``queries`` among ``vectors``, both (row, vec_id, v) and ``vectors`` a cut."""
    data, asked, width, _ = voronoi_tiles(vectors, queries, k, pivots, shard, block)

    def solve(left: pa.Table, right: pa.Table) -> pa.Table:
        empty = _FOUND.fieldNames()
        if not left.num_rows or not right.num_rows:
            return pa.table({n: pa.array([], pa.int64()) for n in empty})
        x, ids, rows = _matrix(left["v"], width), left["vec_id"].to_numpy(), left["row"].to_numpy()
        q, q_ids, q_rows = _matrix(right["v"], width), right["vec_id"].to_numpy(), right["row"].to_numpy()
        out = []
        for a in range(0, len(q), _ROWS):
            s = _products(q[a : a + _ROWS], x)
            for i in range(len(s)):
                at = _best(s[i], ids, k + 1)
                at = at[rows[at] != q_rows[a + i]][:k]
                out.append(np.stack([np.full(len(at), q_rows[a + i]), np.full(len(at), q_ids[a + i]), ids[at], s[i][at]]))
        cols = np.concatenate(out, axis=1)
        return pa.table(dict(zip(empty, cols, strict=True)))

    keys = ("g", "block", "bin")
    # written out: where one frame is used twice in a plan, the engine may prune what the grouped call reads
    found = cut(data.groupBy(*keys).cogroup(asked.groupBy(*keys)).applyInArrow(solve, _FOUND), "found")
    rank = F.row_number().over(Window.partitionBy("query_row").orderBy(F.col("score").desc(), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_row", "query_id", "rank", "vec_id", "score")


def op3_voronoi_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = cut(integer_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")), "vectors")
    return knn_join(vectors, vectors.where(F.col("vec_id") % 100 == 0)).select("query_id", "rank", "vec_id", "score")


OP3_SQL = """
WITH ok AS (SELECT row_number() OVER () AS rid, vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
q AS (SELECT * FROM ok WHERE vec_id % 100 = 0),
s AS (SELECT q.rid, q.vec_id AS query_id, o.vec_id, list_inner_product(q.v::DOUBLE[], o.v::DOUBLE[])::BIGINT AS score FROM q JOIN ok o ON o.rid <> q.rid)
SELECT query_id, row_number() OVER (PARTITION BY rid ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM s
QUALIFY row_number() OVER (PARTITION BY rid ORDER BY score DESC, vec_id) <= 10
"""
