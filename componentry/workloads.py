"""The experiments: graphs from the tables and from generators, method comparisons, sweeps of measures."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from componentry.functions.graphs import Graph, graph, sample_edges
from componentry.operators import baselines, components, linkage, measures, secondary_sort
from componentry.operators.stops import DistanceStop, SizeStop
from componentry.plans.rounds import Loop, RunResult
from componentry.plans.storage import cut, release
from componentry.sources import builders, generators
from componentry.sources.io import read_table

Build = Callable[[SparkSession, str], DataFrame]


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    orders = read_table(spark, d, "orders", ["o_orderkey", "o_custkey"])
    items = read_table(spark, d, "lineitem", ["l_orderkey", "l_partkey"])
    return builders.bipartite(orders.join(items, F.col("o_orderkey") == F.col("l_orderkey")), "o_custkey", "l_partkey")


def customer_part_sparse(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of customer_part kept at 2 % by a rule over both keys."""
    a, b = F.expr("least(src, dst)"), F.expr("greatest(src, dst)")
    cust, part = F.when(a % 2 == 0, a).otherwise(b) / 2, (F.when(a % 2 == 0, b).otherwise(a) - 1) / 2
    return customer_part(spark, d).where(F.pmod(cust.cast("long") * 7919 + part.cast("long") * 104729, F.lit(1000)) < 20)


def part_supplier(spark: SparkSession, d: str) -> DataFrame:
    return builders.bipartite(read_table(spark, d, "lineitem", ["l_partkey", "l_suppkey"]), "l_partkey", "l_suppkey")


def part_supplier_sparse(spark: SparkSession, d: str) -> DataFrame:
    items = read_table(spark, d, "lineitem", ["l_partkey", "l_suppkey", "l_quantity", "l_returnflag"])
    return builders.bipartite(items.where("l_quantity = 50 and l_returnflag = 'R'"), "l_partkey", "l_suppkey")


def order_chain_customer(spark: SparkSession, d: str) -> DataFrame:
    orders = read_table(spark, d, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    return builders.chain(orders, "o_orderkey", ["o_orderdate", "o_orderkey"], ["o_custkey"])


def order_chain_global(spark: SparkSession, d: str) -> DataFrame:
    return builders.chain(read_table(spark, d, "orders", ["o_orderkey", "o_orderdate"]), "o_orderkey", ["o_orderdate", "o_orderkey"])


def order_chain_dealt(spark: SparkSession, d: str) -> DataFrame:
    """order_chain_global with the edges of a stretch of time side by side."""
    return builders.chain(read_table(spark, d, "orders", ["o_orderkey", "o_orderdate"]), "o_orderkey", ["o_orderdate", "o_orderkey"], dealt=True)


def doc_exact(spark: SparkSession, d: str) -> DataFrame:
    return builders.share_key(read_table(spark, d, "documents", ["doc_id", "text"]), "doc_id", "text")


def _long_lines(spark: SparkSession, d: str) -> DataFrame:
    docs = read_table(spark, d, "documents", ["doc_id", "text"]).select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return docs.where(F.length("line") >= 40)


def doc_line(spark: SparkSession, d: str) -> DataFrame:
    """Documents that share a line of 40 characters or more."""
    return builders.share_key(_long_lines(spark, d), "doc_id", "line")


def doc_jaccard(spark: SparkSession, d: str) -> DataFrame:
    return builders.jaccard(read_table(spark, d, "documents", ["doc_id", "text"]), "doc_id", "text")


def page_link(spark: SparkSession, d: str) -> DataFrame:
    return builders.page_link(read_table(spark, d, "pages", ["page_id", "html"]))


def embedding_cos(spark: SparkSession, d: str) -> DataFrame:
    return builders.cosine(read_table(spark, d, "embeddings", ["vec_id", "embedding"]), "vec_id", "embedding", 40)


def event_chain(spark: SparkSession, d: str) -> DataFrame:
    events = read_table(spark, d, "events", ["event_id", "ts", "user_id"])
    return builders.chain(events, "event_id", ["ts", "event_id"], ["user_id"], "6 hours", "ts")


def event_json(spark: SparkSession, d: str) -> DataFrame:
    return builders.json_key(read_table(spark, d, "events", ["event_id", "user_id", "props"]))


def event_type(spark: SparkSession, d: str) -> DataFrame:
    return builders.share_key(read_table(spark, d, "events", ["event_id", "user_id", "event_type"]), "event_id", "user_id", "event_type")


def event_within(spark: SparkSession, d: str) -> DataFrame:
    events = read_table(spark, d, "events", ["event_id", "ts", "user_id"])
    return builders.within(events, "event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")) / 1e6, 3600)


def conversation_chain(spark: SparkSession, d: str) -> DataFrame:
    turns = read_table(spark, d, "conversations", ["conv_id", "turn"]).withColumn("id", F.col("conv_id") * 1000 + F.col("turn"))
    return builders.chain(turns, "id", ["turn"], ["conv_id"])


def passage(spark: SparkSession, d: str) -> DataFrame:
    return builders.passage(read_table(spark, d, "documents", ["doc_id", "text"]), read_table(spark, d, "benchmark", ["item_id", "text"]))


def part_tree(spark: SparkSession, d: str) -> DataFrame:
    """Complete binary tree over the part keys, which are dense ranks: key -> half of it."""
    return read_table(spark, d, "part", ["p_partkey"]).where("p_partkey >= 2").select(F.expr("p_partkey div 2").alias("src"), F.col("p_partkey").alias("dst"))


GRAPHS: dict[str, Build] = {
    f.__name__: f
    for f in (customer_part, customer_part_sparse, part_supplier, part_supplier_sparse, order_chain_customer, order_chain_global, doc_exact, doc_line, doc_jaccard, page_link, embedding_cos, event_chain, event_json, event_type, event_within, conversation_chain, passage, part_tree)
}


def part_supplier_price(spark: SparkSession, d: str) -> DataFrame:
    """Weighted pairs: the least unit price of a part from a supplier, in cents."""
    items = read_table(spark, d, "lineitem", ["l_partkey", "l_suppkey", "l_extendedprice", "l_quantity"])
    return items.groupBy((F.col("l_partkey") * 2).alias("a"), (F.col("l_suppkey") * 2 + 1).alias("b")).agg(F.min(F.floor(F.col("l_extendedprice") * 100 / F.col("l_quantity")).cast("double")).alias("w")).select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "w")


def order_gap(spark: SparkSession, d: str) -> DataFrame:
    """Weighted chain of each customer's orders: days between."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    orders = read_table(spark, d, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    rows = orders.select("o_orderkey", F.lead("o_orderkey").over(w).alias("n"), F.datediff(F.lead("o_orderdate").over(w), F.col("o_orderdate")).cast("double").alias("w")).where("n is not null")
    return rows.select(F.least("o_orderkey", "n").alias("src"), F.greatest("o_orderkey", "n").alias("dst"), "w")


#: rows that a round of all_members may send
MEMBER_CAP = 20_000_000

METHODS: dict[str, Callable[[Graph], RunResult]] = {
    "neighbor_min": lambda g: components.neighbor_min(g),
    "all_members": lambda g: components.all_members(g, member_cap=MEMBER_CAP),
    "min_owner": lambda g: components.min_owner(g),
    "min_owner_sorted": lambda g: secondary_sort.min_owner_sorted(g),
    "min_owner_balanced": lambda g: components.min_owner_balanced(g, precontract=True),
    "min_owner_balanced_plain": lambda g: components.min_owner_balanced(g),
    "min_owner_random": lambda g: components.min_owner(g, order="random"),
    "upper_core": lambda g: components.upper_core(g),
    "label_prop": lambda g: baselines.label_prop_baseline(g),
    "superstep": lambda g: baselines.superstep_min(g),
}

GROUP_1 = (("doc_exact", "doc_line", "customer_part_sparse"), ("label_prop", "min_owner", "upper_core", "all_members"))
GROUP_2 = (("customer_part", "part_supplier", "part_supplier_sparse"), ("label_prop", "min_owner_balanced", "min_owner_balanced_plain"))


def _outcome(components: DataFrame) -> tuple[int, int, int]:
    """Vertices, largest component and number of components."""
    row = measures.component_sizes(components).agg(F.sum("size"), F.max("size"), F.count(F.lit(1))).first()
    return row[0] or 0, row[1] or 0, row[2]


def _outcomes(runs: list[DataFrame]) -> list[tuple[int, int, int]]:
    """_outcome of each of ``runs``, in one query over all of them."""
    every = reduce(DataFrame.unionByName, (c.select(F.lit(k).alias("run"), "component") for k, c in enumerate(runs)))
    sizes = every.groupBy("run", "component").agg(F.count(F.lit(1)).alias("size"))
    found = {r[0]: tuple(r[1:]) for r in sizes.groupBy("run").agg(F.sum("size"), F.max("size"), F.count(F.lit(1))).collect()}  # a row for each run
    return [found.get(k, (0, 0, 0)) for k in range(len(runs))]


def compare(spark: SparkSession, d: str, group: tuple = GROUP_1, repeats: int = 4) -> DataFrame:
    """A comparison table: a row for each workload and method, seconds the mean of ``repeats`` runs, jobs those of the first."""
    rows = []
    for name in group[0]:
        edges = cut(GRAPHS[name](spark, d).select("src", "dst"), name)
        for method in group[1]:
            got = measures.timed(lambda e=edges, m=method: METHODS[m](Graph(e)), repeats, spark)
            v, n, c = _outcome(got["components"]) if not got["dnf"] else (None, None, None)
            rows.append((name, method, v, edges.count(), n, c, bool(got["dnf"]), got.get("rounds_run"), got.get("rounds_productive"), got.get("jobs"), got.get("peak_messages"), got.get("peak_state_rows"), float(got["seconds"])))
    return spark.createDataFrame(rows, "workload string, method string, v long, e long, largest long, n_components long, dnf boolean, rounds_run int, rounds_productive int, jobs int, peak_messages long, peak_state_rows long, seconds double")


def sweep(spark: SparkSession, shape: str = "path", powers: range = range(5, 20), orders: int = 10) -> DataFrame:
    """Rounds and peak data of min_owner on paths or trees of 2^k vertices: the worst and the mean of ``orders`` random vertex orders.

    The orders of a size run side by side as one graph of so many copies; after each round every copy's rows are counted and
    fingerprinted alone, which tells its own rounds and peak.
    """
    rows = []
    for p in powers:
        n = 1 << p
        edges = generators.path(spark, n) if shape == "path" else generators.tree(spark, n - 1)
        v, e, d = (n, n - 1, n - 1) if shape == "path" else (n - 1, n - 2, 2 * (p - 1))
        ids = graph(edges).ids.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(orders - 1))))
        order = Window.partitionBy("copy").orderBy(F.xxhash64("copy", "id"), "id")
        book = cut(ids.select("copy", "id", (F.col("copy").cast("long") * (1 << 40) + F.row_number().over(order)).alias("rank")), "orders")
        a, b = book.select("copy", F.col("id").alias("src"), F.col("rank").alias("a")), book.select("copy", F.col("id").alias("dst"), F.col("rank").alias("b"))
        copies = cut(edges.join(a, "src").join(b, ["copy", "dst"]).select(F.col("a").alias("src"), F.col("b").alias("dst")), "copies")
        seen: dict[int, list[tuple]] = {c: [] for c in range(orders)}

        def count(loop: Loop, seen: dict = seen) -> bool:
            part = F.expr("key div 1099511627776").alias("copy")
            for r in loop.state.groupBy(part).agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("key", "member").cast("decimal(38,0)")).alias("h")).collect():  # a row for each copy
                seen[r["copy"]].append((r["n"], r["h"]))
            return False

        run = components.min_owner(graph(copies), after=count)
        productive = [sum(x != y for x, y in zip(own, own[1:], strict=False)) for own in seen.values()]
        peaks = [max(x[0] for x in own) / (v + e) for own in seen.values()]
        whole = _outcome(run.components)
        release(book, copies)
        bound = 2 * math.log2(d)
        rows.append((shape, p, v, e, d, orders, whole[2], max(productive), run.rounds_run, bound, max(productive) <= bound, round(sum(peaks) / orders, 4), round(max(peaks), 4), sum(peaks) / orders <= 3.0))
    return spark.createDataFrame(rows, "shape string, power int, v long, e long, d long, orders int, n_components long, worst_rounds int, rounds_run int, two_log_d double, rounds_within boolean, mean_peak double, worst_peak double, data_within boolean")


def sparsify(spark: SparkSession, d: str, names: tuple = ("customer_part", "part_supplier"), percents: tuple = (50, 10, 5, 2, 1)) -> DataFrame:
    """Edges, components, diameter (double sweep from the least id) and rounds as edges are sampled away."""
    rows = []
    for name in names:
        edges = cut(GRAPHS[name](spark, d).select("src", "dst"), name)
        whole = {100: edges}
        for p in sorted(percents, reverse=True):  # a share holds every smaller one
            whole[p] = cut(sample_edges(whole[min(q for q in whole if q >= p)], p), "sample")
        for p in percents:
            run = components.min_owner(Graph(whole[p]))
            rows.append((name, p, whole[p].count(), *_outcome(run.components), measures.diameter(whole[p], components=run.components), run.rounds_run))
        release(*whole.values())
    return spark.createDataFrame(rows, "workload string, percent int, e long, v long, largest long, n_components long, diameter int, rounds_run int")


STOPS = (*(DistanceStop(t) for t in (0.2, 0.5, 0.8)), *(SizeStop(k) for k in (2, 5, 20)))


def clustering(spark: SparkSession, d: str, hashings: tuple = ("min_owner", "all_members"), names: tuple = ("doc_jaccard", "embedding_cos"), stops: tuple = STOPS) -> DataFrame:
    """Rounds, seconds and clusters of single linkage by workload, stop test and hashing. Every run goes to its end: one that does not fails the table."""
    rows = []
    for name in names:
        wedges = cut(GRAPHS[name](spark, d).select("src", "dst", "w"), name)
        for stop in stops:
            kind, at = ("distance", float(stop.theta)) if isinstance(stop, DistanceStop) else ("size", float(stop.k))
            for h in hashings:
                got = measures.timed(lambda w=wedges, s=stop, h=h: linkage.slc_rounds(w, s, hashing=h), whole=True)
                rows.append((name, kind, at, h, *_outcome(got["components"]), bool(got["dnf"]), got["rounds_run"], float(got["seconds"])))
    return spark.createDataFrame(rows, "workload string, stop string, at double, hashing string, v long, largest long, n_clusters long, dnf boolean, rounds_run int, seconds double")


KS = (1, 5, 10, 15)


def contention(spark: SparkSession, d: str, ks: tuple = KS, name: str = "doc_line") -> DataFrame:
    """Largest and median seconds of k simultaneous runs, files each round against resident supersteps; each run's result is looked at."""
    edges = cut(GRAPHS[name](spark, d).select("src", "dst"), name)
    rows = []
    for k in ks:
        for method in ("min_owner", "superstep"):
            got = measures.contention(lambda m=method: METHODS[m](Graph(edges)), k)
            ends = _outcomes(got["components"])
            rows.append((method, k, len(ends), min(e[0] for e in ends), min(e[1] for e in ends), min(e[2] for e in ends), len(set(ends)) == 1, got["max"], got["median"]))
    return spark.createDataFrame(rows, "method string, k int, n_runs int, v long, largest long, n_components long, all_agree boolean, max_s double, median_s double")
