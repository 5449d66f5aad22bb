"""Synthetic graphs as distributed ranges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from componentry.functions.graphs import normalize_edges


def path(spark: SparkSession, n: int) -> DataFrame:
    """0 - 1 - ... - (n - 1)."""
    return spark.range(max(0, n - 1)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))


def tree(spark: SparkSession, n: int) -> DataFrame:
    """Complete binary tree of ids 1..n; each id hangs on the half of it."""
    return spark.range(2, n + 1).select(F.expr("id div 2").alias("src"), F.col("id").alias("dst"))


def star(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(1, n).select(F.lit(0).cast("bigint").alias("src"), F.col("id").alias("dst"))


def cycle(spark: SparkSession, n: int) -> DataFrame:
    return normalize_edges(spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst")))


def clique(spark: SparkSession, n: int) -> DataFrame:
    """Every pair; for small ``n`` only, as its size is its definition."""
    return spark.range(n).select(F.col("id").alias("src"), F.explode(F.sequence(F.col("id"), F.lit(n))).alias("dst")).where("dst > src and dst < " + str(n))


def grid(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    ids = spark.range(rows * cols)
    right = ids.where(F.col("id") % cols != cols - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    down = ids.where(F.col("id") < (rows - 1) * cols).select(F.col("id").alias("src"), (F.col("id") + cols).alias("dst"))
    return right.unionByName(down)


def random_graph(spark: SparkSession, n: int, m: int, seed: int = 42) -> DataFrame:
    """``m`` draws of two ends by hash; loops and repeats fall away."""
    end = lambda k: F.pmod(F.xxhash64(F.lit(seed), F.lit(k), "id"), F.lit(n))
    return normalize_edges(spark.range(m).select(end(1).alias("src"), end(2).alias("dst")))


# -- the same shapes over the ids (0 or more) of a table


def _linked(ids: DataFrame, to: str, where: str = "true") -> DataFrame:
    """Each id that ``where`` takes to the id ``to``, if that is there."""
    ids = ids.where("id is not null").distinct()
    ends = ids.where(where).select(F.col("id").alias("x"), F.expr(to).alias("y"))
    return ends.join(ids.withColumnRenamed("id", "y"), "y").select(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst"))


def star_over(ids: DataFrame) -> DataFrame:
    """The least id to all others."""
    ids = ids.where("id is not null").distinct()
    least = ids.agg(F.min("id").alias("src"))
    return ids.join(F.broadcast(least), F.col("id") > F.col("src")).select("src", F.col("id").alias("dst"))


def cycle_over(ids: DataFrame) -> DataFrame:
    """The path, and its ends where there are more than two ids."""
    ends = ids.agg(F.min("id").alias("src"), F.max("id").alias("dst"), F.countDistinct("id").alias("n")).where("n > 2").select("src", "dst")
    return _linked(ids, "id + 1").unionByName(ends)


def cliques_over(ids: DataFrame, n: int = 10) -> DataFrame:
    """All pairs of each ``n`` ids in a row."""
    rows = ids.where("id is not null").distinct().withColumn("b", F.floor(F.col("id") / n))
    return rows.withColumnRenamed("id", "src").join(rows.withColumnRenamed("id", "dst"), "b").where("src < dst").select("src", "dst")


OVER = {
    "path": lambda ids: _linked(ids, "id + 1"),
    "tree": lambda ids: _linked(ids, "id div 2", "id >= 2"),
    "star": star_over,
    "cycle": cycle_over,
    "clique": cliques_over,
    "grid": lambda ids: _linked(ids, "id + 1", "id % 30 <> 29").unionByName(_linked(ids, "id + 30")),
}
