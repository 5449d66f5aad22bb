"""Narrow graph transformations: normal forms, sampling, relabelling, profiles of the raw edge list."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from componentry.schemas import require


class NullIdError(ValueError):
    """An edge or vertex has no id."""


def normalize_edges(df: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """Canonical undirected edges: src < dst, no loops, no repeats; rows with a null end are dropped."""
    a, b = F.col(src), F.col(dst)
    return df.where(a != b).select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).distinct()


def normalize_wedges(df: DataFrame, w: str = "w") -> DataFrame:
    """Canonical weighted edges; of parallel edges the least weight stays."""
    a, b = F.col("src"), F.col("dst")
    ends = (F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"))
    return df.where((a != b) & F.col(w).isNotNull()).select(*ends, F.col(w).alias("w")).groupBy("src", "dst").agg(F.min("w").alias("w"))


def validate(edges: DataFrame) -> DataFrame:
    """Pass ``edges`` on, failing the job at the first null id."""
    no_null = lambda c: F.when(F.col(c).isNull(), F.raise_error(F.lit("null id in " + c))).otherwise(F.col(c)).alias(c)
    return edges.select(*(no_null(c) if c in ("src", "dst") else F.col(c) for c in edges.columns))


def null_report(edges: DataFrame) -> DataFrame:
    """One row: edges, null ends, loops."""
    return edges.agg(
        F.count(F.lit(1)).alias("n_rows"),
        F.count_if(F.col("src").isNull() | F.col("dst").isNull()).alias("n_null"),
        F.count_if(F.col("src") == F.col("dst")).alias("n_loops"),
    )


def adjacency(edges: DataFrame) -> DataFrame:
    """Both directions of each edge as (id, nbr), from one scan of the edges."""
    two = F.array(F.struct(F.col("src").alias("id"), F.col("dst").alias("nbr")), F.struct(F.col("dst").alias("id"), F.col("src").alias("nbr")))
    return edges.select(F.explode(two).alias("x")).select("x.id", "x.nbr")


def touched(edges: DataFrame) -> DataFrame:
    """Ids that an edge has."""
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def isolated(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    return vertices.join(touched(edges), "id", "left_anti")


@dataclass
class Graph:
    """Canonical edges, and the vertex ids; without ``vertices`` those that an edge touches."""

    edges: DataFrame
    vertices: DataFrame | None = None

    @property
    def ids(self) -> DataFrame:
        return touched(self.edges) if self.vertices is None else self.vertices.select("id").distinct()


def graph(edges: DataFrame, vertices: DataFrame | None = None) -> Graph:
    return Graph(normalize_edges(require(edges, "src", "dst")), vertices)


def induced(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges with both ends among ``ids``."""
    ids = ids.select("id")
    return edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi").select(*edges.columns)


def lighter(wedges: DataFrame, theta: float) -> DataFrame:
    """Edges of weight at most ``theta``; the predicate reaches the scan."""
    return wedges.where(F.col("w") <= theta)


def sample_edges(edges: DataFrame, percent: int, seed: int = 42) -> DataFrame:
    """A fixed share of the edges by a digest of both ends: the same edges at every run and in any engine, nested in larger shares."""
    digest = F.md5(F.concat_ws(":", F.lit(seed), "src", "dst"))
    return edges.where(F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % 10_000 < percent * 100)


def mix64(x: Column, seed: int) -> Column:
    """A seeded bijection of the 64-bit integers: a Feistel network over the two halves, no table and no sort."""
    low = 0xFFFFFFFF
    left, right = F.shiftrightunsigned(x, 32), x.bitwiseAND(F.lit(low))
    for k in range(4):
        left, right = right, left.bitwiseXOR(F.xxhash64(F.lit(seed), F.lit(k), right).bitwiseAND(F.lit(low)))
    return F.shiftleft(left, 32).bitwiseOR(right)


def relabel(edges: DataFrame, mode: str = "mix", seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """A random vertex order: (edges over ranks, dictionary(id, rank)).

    ``mix`` maps ids by a 64-bit bijection without a sort; ``rank`` gives dense ranks 0..V-1 of a seeded
    hash order, by a range sort in parts whose sizes are added up, so no single task sees all ids.
    """
    ids = touched(edges)
    if mode == "mix":
        book = ids.select("id", mix64(F.col("id"), seed).alias("rank"))
        return edges.select(mix64(F.col("src"), seed).alias("src"), mix64(F.col("dst"), seed).alias("dst"), *(c for c in edges.columns if c not in ("src", "dst"))), book
    if mode != "rank":
        raise ValueError(mode)
    book = dense_rank(ids.select("id", F.xxhash64(F.lit(seed), "id").alias("h")), "h", "id").select("id", "rank")
    out = edges
    for end in ("src", "dst"):
        out = out.join(book.select(F.col("id").alias(end), F.col("rank").alias(end + "_r")), end).drop(end).withColumnRenamed(end + "_r", end)
    return out.select("src", "dst", *(c for c in edges.columns if c not in ("src", "dst"))), book


def dense_rank(df: DataFrame, *order: str) -> DataFrame:
    """``df`` with ``rank`` 0..n-1 by ``order``, whose first column is an evenly spread 64-bit hash.

    The hash's top 12 bits cut the rows into ordered parts; each part is ranked alone and shifted by the
    rows of the parts before it.
    """
    part = F.shiftright(F.col(order[0]), 52)
    df = df.withColumn("_part", part)
    sizes = df.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = sizes.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    inner = Window.partitionBy("_part").orderBy(*order)
    return df.withColumn("_r", F.row_number().over(inner)).join(F.broadcast(base), "_part").withColumn("rank", F.col("_base") + F.col("_r") - 1).drop("_part", "_r", "_base")


def encode(df: DataFrame, *columns: str) -> tuple[DataFrame, DataFrame]:
    """A dictionary of the distinct values of ``columns``: (value, id) with id a 64-bit hash, and the collisions found.

    The second frame is empty unless two values share a hash; callers refuse to go on in that case.
    """
    values = df.select(F.explode(F.array(*(F.col(c).cast("string") for c in columns))).alias("value")).where("value is not null").distinct()
    book = values.select("value", F.xxhash64("value").alias("id"))
    clashes = book.groupBy("id").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    return book, clashes


def union_edges(*parts: DataFrame) -> DataFrame:
    out = parts[0].select("src", "dst")
    for p in parts[1:]:
        out = out.unionByName(p.select("src", "dst"))
    return normalize_edges(out)
