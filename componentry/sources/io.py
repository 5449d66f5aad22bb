"""Sources and sinks: tables, edge lists in text, JSON, ORC and Parquet, neighbour lists, component tables, round stores."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.plans.storage import drop_path, shared_dir
from componentry.schemas import EDGES, WEDGES, require


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A table of the test data; only ``columns`` are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edge_text(spark: SparkSession, path: str, sep: str = "\t", schema: T.StructType = EDGES, header: bool = False, comment: str = "#") -> DataFrame:
    """Edges as separated text. A schema is given, so nothing is inferred; lines that do not fit it fail the read."""
    return spark.read.schema(schema).options(sep=sep, header=header, comment=comment, mode="FAILFAST").csv(path)


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType = EDGES) -> DataFrame:
    """Edges as parquet, orc, json or csv."""
    return spark.read.schema(schema).format(fmt).load(path)


def read_wedges(df: DataFrame, w_col: str, src: str = "src", dst: str = "dst") -> DataFrame:
    return df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), F.col(w_col).cast(WEDGES["w"].dataType).alias("w"))


def read_adjacency(df: DataFrame, id_col: str = "id", list_col: str = "nbrs") -> DataFrame:
    """Neighbour lists (id, array) as edges; a vertex with an empty list keeps a loop, which names it."""
    return df.select(F.col(id_col).alias("src"), F.explode_outer(list_col).alias("dst")).select("src", F.coalesce("dst", "src").alias("dst"))


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    require(edges, "src", "dst").write.mode(mode).format(fmt).save(path)


def write_components(components: DataFrame, path: str | None = None, table: str | None = None, buckets: int | None = None, parts: int | None = None, mode: str = "errorifexists") -> None:
    """Components as Parquet files in ``parts`` folders of a component hash, or as a table bucketed by id for later joins without exchange."""
    if table is not None:
        components.write.mode(mode).bucketBy(buckets or 64, "id").sortBy("id").saveAsTable(table)
        return
    if parts:
        dealt = components.withColumn("part", F.pmod(F.xxhash64("component"), F.lit(parts)))
        dealt.repartition("part").write.mode(mode).partitionBy("part").parquet(path)
    else:
        components.write.mode(mode).parquet(path)


class RoundStore:
    """Generations of a state on shared storage: a run can go on from its last full round."""

    def __init__(self, spark: SparkSession, name: str, path: str | None = None):
        self.spark, self.base = spark, f"{path or shared_dir(spark)}/rounds-{name}"

    def save(self, r: int, state: DataFrame) -> DataFrame:
        state.write.mode("overwrite").parquet(f"{self.base}/{r}")
        self.drop(r - 2)
        return self.load(r)

    def load(self, r: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.base}/{r}")

    def rounds(self) -> list[int]:
        """Rounds that were written in full."""
        hadoop = self.spark._jvm.org.apache.hadoop.fs.Path(self.base)
        fs = hadoop.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(hadoop):
            return []
        done = (s.getPath() for s in fs.listStatus(hadoop))
        marker = self.spark._jvm.org.apache.hadoop.fs.Path
        return sorted(int(p.getName()) for p in done if fs.exists(marker(p, "_SUCCESS")))

    def drop(self, r: int) -> None:
        if r >= 0:
            drop_path(self.spark, f"{self.base}/{r}")
