"""Measures over graphs, components and runs."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from componentry.functions.graphs import Graph, adjacency
from componentry.plans.rounds import NotConverged, RunResult
from componentry.plans.storage import cut, release

# -- components


def component_sizes(components: DataFrame) -> DataFrame:
    return components.groupBy("component").agg(F.count(F.lit(1)).alias("size"))


def size_histogram(components: DataFrame) -> DataFrame:
    return component_sizes(components).groupBy("size").agg(F.count(F.lit(1)).alias("n_components"))


def largest(components: DataFrame) -> DataFrame:
    return component_sizes(components).agg(F.max("size").alias("n"), F.count(F.lit(1)).alias("n_components"))


def topk(components: DataFrame, k: int) -> DataFrame:
    """The ``k`` largest components; ties to the smaller name."""
    return component_sizes(components).orderBy(F.desc("size"), "component").limit(k)


def rank_components(components: DataFrame) -> DataFrame:
    """Rank by size, and the running share of vertices. Sizes are ranked as a histogram, so the one task has a row per distinct size."""
    hist = size_histogram(components)
    w = Window.orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return hist.select("size", "n_components", (F.sum("n_components").over(w) - F.col("n_components") + 1).alias("rank"), F.sum(F.col("size") * F.col("n_components")).over(w).alias("running_vertices"))


def members(components: DataFrame, cap: int = 1000) -> DataFrame:
    """(component, part, members): sorted lists of at most ``cap`` ids. A component of up to ``cap`` ids is part 0; a larger one is cut
    into ranges of ``cap`` id values, one part each, so parts in order are its members in order and no row or task holds it whole."""
    sized = components.join(component_sizes(components), "component")
    part = F.when(F.col("size") <= cap, F.lit(0).cast("long")).otherwise(F.expr(f"(id - pmod(id, {cap})) div {cap}"))
    return sized.groupBy("component", part.alias("part")).agg(F.sort_array(F.collect_set("id")).alias("members"))


def attach(df: DataFrame, components: DataFrame, id_col: str, how: str = "left") -> DataFrame:
    """``df`` with the component of ``id_col``."""
    return df.join(components.withColumnRenamed("id", id_col), id_col, how)


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 16, how: str = "inner") -> DataFrame:
    """Equi-join with ``left`` rows of a hot key spread over ``salts`` tasks; ``right``, the side with few rows a key, is repeated for each."""
    spread = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    copies = right.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return spread.join(copies, [key, "_salt"], how).drop("_salt")


def percentiles(df: DataFrame, components: DataFrame, id_col: str, value: str, at: tuple = (0.25, 0.5, 0.75)) -> DataFrame:
    """Exact percentiles of ``value`` in each component, each a value that occurs."""
    return attach(df, components, id_col, "inner").groupBy("component").agg(*(F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY `{value}`)").alias(f"p{round(100 * p)}") for p in at))


def density(profile_row: DataFrame) -> DataFrame:
    """``profile`` with the share of all vertex pairs that are edges, and the mean degree."""
    v, e = F.col("v"), F.col("e")
    return profile_row.withColumn("density", F.when(v > 1, 2 * e / (v * (v - 1)))).withColumn("mean_degree", 2 * e / v)


def summarise(df: DataFrame, components: DataFrame, id_col: str, value: str) -> DataFrame:
    """Per component: rows, sum, extremes, median, and the row of the greatest value."""
    return attach(df, components, id_col, "inner").groupBy("component").agg(
        F.count(F.lit(1)).alias("n_rows"),
        F.sum(F.col(value).cast("decimal(18,2)")).alias("total"),
        F.min(value).alias("least"),
        F.max(value).alias("most"),
        F.max(F.struct(F.col(value), F.col(id_col)))[id_col].alias("top_id"),
        F.bool_and(F.col(value) > 0).alias("all_positive"),
    )


def rollup(df: DataFrame, components: DataFrame, id_col: str, *columns: str) -> DataFrame:
    """Rows and components at every level of ``columns``."""
    return attach(df, components, id_col, "inner").rollup(*columns).agg(F.count(F.lit(1)).alias("n_rows"), F.countDistinct("component").alias("n_components"), F.grouping_id().alias("level"))


def cube(df: DataFrame, components: DataFrame, id_col: str, *columns: str) -> DataFrame:
    return attach(df, components, id_col, "inner").cube(*columns).agg(F.count(F.lit(1)).alias("n_rows"), F.countDistinct("component").alias("n_components"), F.grouping_id().alias("level"))


def topk_within(df: DataFrame, components: DataFrame, id_col: str, value: str, k: int) -> DataFrame:
    """The ``k`` rows of the greatest ``value`` in each component."""
    w = Window.partitionBy("component").orderBy(F.desc(value), id_col)
    return attach(df, components, id_col, "inner").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("component", "rank", id_col, value)


def rolling(df: DataFrame, part: str, seconds, span: int) -> DataFrame:
    """Rows of the same ``part`` in the ``span`` seconds before each row, itself included."""
    w = Window.partitionBy(part).orderBy(seconds).rangeBetween(-span, 0)
    return df.withColumn("n_recent", F.count(F.lit(1)).over(w))


def label_asof(events: DataFrame, labels: DataFrame, key: str, ts: str) -> DataFrame:
    """The label (key, since, label) in force at each event: both in one ordered pass, the last label carried on."""
    common = [c for c in events.columns if c not in (key, ts)]
    rows = events.select(key, F.col(ts).alias("_at"), F.lit(1).alias("_side"), F.struct(*common).alias("_row"), F.lit(None).cast("long").alias("_label"))
    marks = labels.select(F.col(key), F.col("since").alias("_at"), F.lit(0).alias("_side"), F.lit(None).cast(rows.schema["_row"].dataType).alias("_row"), F.col("label").cast("long").alias("_label"))
    w = Window.partitionBy(key).orderBy("_at", "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = rows.unionByName(marks).withColumn("label", F.last("_label", ignorenulls=True).over(w)).where("_side = 1")
    return out.select(key, F.col("_at").alias(ts), "_row.*", "label")


# -- graphs


def degrees(edges: DataFrame) -> DataFrame:
    return adjacency(edges).groupBy("id").agg(F.count(F.lit(1)).alias("degree"))


def hubs(edges: DataFrame, k: int) -> DataFrame:
    return degrees(edges).orderBy(F.desc("degree"), "id").limit(k)


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("degree").agg(F.count(F.lit(1)).alias("n_vertices"))


def profile(edges: DataFrame, components: DataFrame) -> DataFrame:
    """One row: v, e, n (largest), n_components, max_degree."""
    d = degrees(edges).agg(F.count(F.lit(1)).alias("touched"), F.max("degree").alias("max_degree"), (F.sum("degree") / 2).cast("long").alias("e"))
    c = component_sizes(components).agg(F.sum("size").alias("v"), F.max("size").alias("n"), F.count(F.lit(1)).alias("n_components"))
    return c.crossJoin(d).select("v", "e", "n", "n_components", "max_degree")  # one row each


def approx_vertices(edges: DataFrame, rsd: float = 0.02) -> DataFrame:
    return adjacency(edges).agg(F.approx_count_distinct("id", rsd).alias("v"))


def cut_edges(edges: DataFrame, components: DataFrame) -> DataFrame:
    """Edges whose ends lie in different clusters, with both."""
    a = components.select(F.col("id").alias("src"), F.col("component").alias("c_src"))
    b = components.select(F.col("id").alias("dst"), F.col("component").alias("c_dst"))
    return edges.join(a, "src").join(b, "dst").where("c_src <> c_dst")


def verify(g: Graph, components: DataFrame) -> DataFrame:
    """One row of counts that are all 0 for right components: edges across, names that are no least member, ids lost."""
    across = cut_edges(g.edges, components).agg(F.count(F.lit(1)).alias("edges_across"))
    heads = components.groupBy("component").agg(F.min("id").alias("least")).agg(F.count_if(F.col("least") != F.col("component")).alias("wrong_names"))
    lost = g.ids.join(components, "id", "left_anti").agg(F.count(F.lit(1)).alias("ids_lost"))
    return across.crossJoin(heads).crossJoin(lost)  # one row each


def bfs(edges: DataFrame, sources: DataFrame, max_depth: int = 10_000) -> DataFrame:
    """(id, depth): least number of hops from any of ``sources`` (id), by frontier joins."""
    nbrs = cut(adjacency(edges).repartition("id"), "nbrs")
    seen = cut(sources.select("id", F.lit(0).alias("depth")).distinct(), "bfs")
    depth = 0
    while depth < max_depth:
        step = nbrs.join(seen.where(F.col("depth") == depth), "id").select(F.col("nbr").alias("id")).distinct().join(seen.select("id"), "id", "left_anti")
        fresh = cut(step.withColumn("depth", F.lit(depth + 1)), "frontier")
        if fresh.isEmpty():
            break
        old, seen = seen, cut(seen.unionByName(fresh), "bfs")
        release(old, fresh)
        depth += 1
    release(nbrs)
    return seen


def minimum_rounds(edges: DataFrame, components: DataFrame) -> DataFrame:
    """One row: the most hops from a component's least id, which is the number of productive rounds of neighbor_min."""
    return bfs(edges, components.select(F.col("component").alias("id")).distinct()).agg(F.max("depth").alias("rounds"))


#: edges of a component that one task may hold for both sweeps
SWEEP_EDGES = 1_000_000


def diameter(edges: DataFrame, mode: str = "double_sweep", components: DataFrame | None = None) -> int:
    """Largest eccentricity: a lower bound by two sweeps (exact on trees), or exact by a sweep from every vertex (small graphs).

    The sweeps start from the least id and never leave its component: with ``components`` (id, component) only its edges are
    read, and where they fit a task both sweeps run in it.
    """
    spark = edges.sparkSession
    if mode == "exact":
        return max((bfs(edges, spark.createDataFrame([(r[0],)], "id long")).agg(F.max("depth")).first()[0] for r in adjacency(edges).select("id").distinct().collect()), default=0)
    first = adjacency(edges).agg(F.min("id")).first()[0]
    if first is None:
        return 0
    own = None
    if components is not None:
        own = edges = cut(edges.select("src", "dst").join(components.where(F.col("component") == F.lit(first)).select(F.col("id").alias("src")), "src", "left_semi"), "own-edges")
        if edges.count() <= SWEEP_EDGES and all(kind in ("int", "bigint") for _, kind in edges.dtypes):
            found = edges.coalesce(1).mapInArrow(_two_sweeps, "depth int").first()[0]
            release(own)
            return found
    far = bfs(edges, spark.createDataFrame([(first,)], "id long")).agg(F.max(F.struct("depth", "id")).alias("x")).first()["x"]
    found = bfs(edges, spark.createDataFrame([(far["id"],)], "id long")).agg(F.max("depth")).first()[0]
    release(own)
    return found


def _two_sweeps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The most hops from the vertex that is farthest from the least id (of several, the greatest)."""
    table = pa.Table.from_batches(list(batches))
    src, dst = table["src"].to_numpy(), table["dst"].to_numpy()
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = ends[: len(src)], ends[len(src) :]
    at, nbrs = np.concatenate([a, b]), np.concatenate([b, a])
    nbrs = nbrs[np.argsort(at, kind="stable")]
    count = np.bincount(at, minlength=len(ids))
    begin = np.cumsum(count) - count
    source = depth = 0
    for _ in range(2):
        seen = np.zeros(len(ids), bool)
        seen[source] = True
        front, depth = np.array([source]), 0
        while True:
            n = count[front]
            step = np.unique(nbrs[np.repeat(begin[front] - (np.cumsum(n) - n), n) + np.arange(n.sum())])
            step = step[~seen[step]]
            if not len(step):
                break
            seen[step] = True
            front, depth = step, depth + 1
        source = front[-1]
    yield pa.RecordBatch.from_pydict({"depth": pa.array([depth], pa.int32())})


# -- agreement of clusterings


def pair_agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: pairs together in a, in b, in both, of all; precision, recall and Rand index follow from them. By a contingency table, not by pairs."""
    both = a.select("id", F.col("component").alias("ca")).join(b.select("id", F.col("component").alias("cb")), "id")
    table = both.groupBy("ca", "cb").agg(F.count(F.lit(1)).alias("n"))
    two = lambda c: F.sum((F.col(c) * (F.col(c) - 1) / 2).cast("long"))
    joint = table.agg(two("n").alias("in_both"), F.sum("n").alias("ids"))
    rows = table.groupBy("ca").agg(F.sum("n").alias("n")).agg(two("n").alias("in_a"))
    cols = table.groupBy("cb").agg(F.sum("n").alias("n")).agg(two("n").alias("in_b"))
    out = joint.crossJoin(rows).crossJoin(cols).withColumn("all_pairs", (F.col("ids") * (F.col("ids") - 1) / 2).cast("long"))  # one row each
    ratio = lambda x, y: F.round(F.when(y > 0, x / y).otherwise(1.0), 6)
    agree = F.col("all_pairs") - F.col("in_a") - F.col("in_b") + 2 * F.col("in_both")
    return out.select("in_a", "in_b", "in_both", "all_pairs", ratio(F.col("in_both"), F.col("in_a")).alias("precision"), ratio(F.col("in_both"), F.col("in_b")).alias("recall"), ratio(agree, F.col("all_pairs")).alias("rand_index"))


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Assignments that only one of two component frames has."""
    left, right = a.select("id", "component"), b.select("id", "component")
    return left.exceptAll(right).withColumn("side", F.lit("a")).unionByName(right.exceptAll(left).withColumn("side", F.lit("b")))


# -- runs


def exchange(result: RunResult, v: int, e: int) -> dict:
    """Rounds, peaks and their ratios to V + E of one run."""
    return {
        "rounds_run": result.rounds_run,
        "rounds_productive": result.rounds_productive,
        "peak_state_rows": result.peak_state_rows,
        "peak_messages": result.peak_messages,
        "bytes_per_round": 8 * result.peak_messages,
        "state_ratio": round(result.peak_state_rows / max(1, v + e), 3),
        "message_ratio": round(result.peak_messages / max(1, v + e), 3),
    }


def bounds(n: int, d: int) -> dict:
    """Round bounds that runs are held against."""
    log = lambda x: math.log2(max(2, x))
    return {"2log2_d": 2 * log(d), "4log2_n": 4 * log(n), "3log2_n": 3 * log(n), "d": float(d), "log2_d": log(d)}


def timed(run: Callable[[], RunResult], repeats: int = 1, spark: SparkSession | None = None, time_limit: float | None = None, whole: bool = False) -> dict:
    """Mean seconds, rounds and components of ``run``, and the jobs of its first time where ``spark`` is given; a run that stops at a cap or passes the limit is a DNF. ``whole``: a run that stops fails the caller."""
    seconds, out, jobs = [], None, None
    for k in range(repeats):
        began = time.perf_counter()
        try:
            if k == 0 and spark is not None:
                out, jobs = job_count(spark, run)
            else:
                out = run()
            out.components.count()
        except NotConverged as stop:
            if whole:
                raise
            return {"dnf": True, "why": str(stop), "seconds": round(time.perf_counter() - began, 2)}
        seconds.append(time.perf_counter() - began)
    mean = statistics.mean(seconds)
    return {"dnf": time_limit is not None and mean > time_limit, "seconds": round(mean, 2), "rounds_run": out.rounds_run, "rounds_productive": out.rounds_productive, "peak_state_rows": out.peak_state_rows, "peak_messages": out.peak_messages, "jobs": jobs, "components": out.components}


def job_count(spark: SparkSession, run: Callable[[], RunResult]) -> tuple[RunResult, int]:
    """``run`` under a job group of its own, and how many Spark jobs it took."""
    group = f"count-{time.time_ns()}"
    spark.sparkContext.setJobGroup(group, "measured run")
    try:
        out = run()
        return out, len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def balance(state: DataFrame, key: str = "key") -> DataFrame:
    """One row: most and mean rows of a key, and of a shuffle partition dealt by it."""
    keys = state.groupBy(key).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("max_key"), F.avg("n").alias("mean_key"))
    dealt = int(state.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = state.repartition(dealt, key).groupBy(F.spark_partition_id().alias("p")).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("max_part"), F.avg("n").alias("mean_part"))
    return keys.crossJoin(parts)  # one row each


def contention(run: Callable[[], RunResult], k: int) -> dict:
    """Largest and median seconds of ``k`` simultaneous runs, and the components that each found."""

    def one(_: int) -> tuple[float, DataFrame]:
        began = time.perf_counter()
        out = run().components
        out.count()
        return time.perf_counter() - began, out

    with ThreadPoolExecutor(k) as pool:
        done = list(pool.map(one, range(k)))
    took = [t for t, _ in done]
    return {"k": k, "max": round(max(took), 2), "median": round(statistics.median(took), 2), "components": [c for _, c in done]}
