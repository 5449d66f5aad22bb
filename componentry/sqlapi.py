"""SQL surface: tables as views, components of a query's edges, and functions for small graphs inside a query."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from componentry.operators.components import components as run_components
from componentry.operators.contract import DisjointSets

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@udtf(returnType=T.StructType([T.StructField("id", T.LongType()), T.StructField("component", T.LongType())]))
class ComponentsOf:
    """Table function: components of one small edge list, given as two arrays."""

    def eval(self, src: list[int], dst: list[int]):
        sets = DisjointSets()
        for a, b in zip(src or [], dst or [], strict=True):
            if a is not None and b is not None:
                sets.join(a, b)
        for i in list(sets.up):
            yield i, sets.find(i)


@pandas_udf(T.LongType())
def count_components(src: pd.Series, dst: pd.Series) -> int:
    """Aggregate: the number of components of a group's edges; for groups that fit one worker."""
    sets = DisjointSets()
    for a, b in zip(src, dst, strict=True):
        sets.join(int(a), int(b))
    return len({sets.find(i) for i in list(sets.up)})


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Views of the tables in ``sf_dir``, and the functions components_of and count_components."""
    for name in TABLES if sf_dir else ():
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)
    spark.udtf.register("components_of", ComponentsOf)
    spark.udf.register("count_components", count_components)


def components(spark: SparkSession, edges_sql: str, method: str = "min_owner", view: str | None = None, **opts) -> DataFrame:
    """Components of the (src, dst) rows of a query; with ``view`` the result is named for later queries."""
    out = run_components(spark.sql(edges_sql), method=method, **opts).components
    if view:
        out.createOrReplaceTempView(view)
    return out
