"""min_owner by secondary sort: memory independent of the cluster size.

Values arrive sorted within a key, so repeats are adjacent and the first value is the owner; nothing of a
cluster has to be held. Two back-ends: sorted DataFrame partitions, and an RDD dealt by key and sorted by (key, member).
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.functions.graphs import Graph
from componentry.operators import emit
from componentry.plans.rounds import Loop, RunResult, export_owner_clusters, init_closed


def _scan(rows: Iterator) -> Iterator[tuple]:
    """One pass over rows sorted by (key, member): drops repeats, attaches the first member of the key."""
    key = owner = last = None
    for (k, m), _ in rows:
        if k != key:
            key, owner, last = k, m, None
        if m != last:
            last = m
            yield k, m, owner


def merge_rdd(messages: DataFrame) -> DataFrame:
    spark = messages.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    keyed = messages.rdd.map(lambda r: ((r[0], r[1]), None))
    dealt = keyed.repartitionAndSortWithinPartitions(parts, lambda km: hash(km[0]))
    schema = T.StructType([T.StructField(c, messages.schema["key"].dataType) for c in ("key", "member", "owner")])
    return spark.createDataFrame(dealt.mapPartitions(_scan), schema)


def min_owner_sorted(g: Graph, *, backend: str = "dataframe", order: str = "natural", seed: int = 42, **opts) -> RunResult:
    from componentry.operators.components import _loop, _ordered

    merge = {"dataframe": emit.merge_sorted, "rdd": merge_rdd}[backend]

    def run(g: Graph) -> RunResult:
        # metrics observed on the messages are not reported where rows leave the plan for an RDD
        loop: Loop = _loop("min_owner_sorted", opts | ({"stats": False} if backend == "rdd" else {}))
        loop.start(merge(init_closed(g)))
        loop.until_stable(emit.min_owner, merge)
        return RunResult(export_owner_clusters(loop.state.select("key", "member", F.col("owner"))), loop.stats, {"backend": backend})

    return _ordered(g, order, seed, run)
