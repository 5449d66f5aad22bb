"""Query registry of the library: every method, variant, baseline, measure and operator on the given tables, and SQL for what SQL can express."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from componentry import sqlapi, workloads
from componentry.functions import graphs
from componentry.functions.graphs import Graph, graph
from componentry.operators import baselines, components, linkage, measures, secondary_sort
from componentry.operators.stops import DistanceStop, SizeStop
from componentry.plans.storage import cut, drop_path, shared_dir
from componentry.sources import builders, generators
from componentry.sources.io import read_table
from componentry.streaming import incremental

Query = Callable[[SparkSession, str], DataFrame]

# -- SQL of the graphs: (src, dst) in canonical form

_CANON = "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM ({}) WHERE a <> b"
EDGE_SQL = {
    "customer_part": _CANON.format("SELECT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey"),
    "customer_part_sparse": _CANON.format("SELECT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE (o_custkey * 7919 + l_partkey * 104729) % 1000 < 20"),
    "part_supplier": _CANON.format("SELECT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem"),
    "part_supplier_sparse": _CANON.format("SELECT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem WHERE l_quantity = 50 AND l_returnflag = 'R'"),
    "order_chain_customer": _CANON.format("SELECT o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS b FROM orders"),
    "order_chain_global": _CANON.format("SELECT o_orderkey AS a, lead(o_orderkey) OVER (ORDER BY o_orderdate, o_orderkey) AS b FROM orders"),
    "doc_exact": _CANON.format("SELECT min(doc_id) OVER (PARTITION BY text) AS a, doc_id AS b FROM documents WHERE text IS NOT NULL"),
    "doc_line": _CANON.format(
        "SELECT min(doc_id) OVER (PARTITION BY line) AS a, doc_id AS b FROM (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 40)"
    ),
    "event_chain": _CANON.format(
        "SELECT event_id AS a, CASE WHEN lead(ts) OVER w <= ts + INTERVAL 6 HOUR THEN lead(event_id) OVER w END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"
    ),
    "event_json": _CANON.format("SELECT min(event_id) OVER (PARTITION BY user_id, k) AS a, event_id AS b FROM (SELECT event_id, user_id, regexp_extract(props, '\"k\": *([0-9]+)', 1) AS k FROM events) WHERE k <> ''"),
    "event_type": _CANON.format("SELECT min(event_id) OVER (PARTITION BY user_id, event_type) AS a, event_id AS b FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL"),
    "event_within": _CANON.format("SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y USING (user_id) WHERE y.ts BETWEEN x.ts AND x.ts + INTERVAL 1 HOUR"),
    "conversation_chain": _CANON.format("SELECT conv_id * 1000 + turn AS a, lead(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations"),
    "part_tree": "SELECT p_partkey // 2 AS src, p_partkey AS dst FROM part WHERE p_partkey >= 2",
}
_GRAMS = "SELECT DISTINCT {id} AS id, unnest(list_transform(range(1, len(w) - {k} + 2), lambda i: array_to_string(w[i:i + {k} - 1], ' '))) AS gram FROM (SELECT {id}, list_filter(string_split(replace(lower(text), chr(10), ' '), ' '), lambda x: x <> '') AS w FROM {table})"
# equal sets: the least id stands for all
JACCARD_SQL = f"""
WITH g AS ({_GRAMS.format(id="doc_id", k=3, table="documents")}), sets AS (SELECT id, count(*) AS n, md5(string_agg(gram, chr(31) ORDER BY gram)) AS k FROM g GROUP BY id), rep AS (SELECT id, n, min(id) OVER (PARTITION BY k) AS c FROM sets),
r AS (SELECT g.id, gram FROM g JOIN rep USING (id) WHERE id = c), p AS (SELECT x.id AS src, y.id AS dst, count(*) AS shared FROM r x JOIN r y USING (gram) WHERE x.id < y.id GROUP BY x.id, y.id)
SELECT src, dst, shared, a.n AS n_src, b.n AS n_dst, round(1 - shared / (a.n + b.n - shared), 6) AS w FROM p JOIN rep a ON a.id = src JOIN rep b ON b.id = dst WHERE shared * 2 >= a.n + b.n - shared
UNION ALL SELECT c, id, n, n, n, 0.0 FROM rep WHERE id <> c"""
EDGE_SQL["doc_jaccard"] = JACCARD_SQL
EDGE_SQL["passage"] = _CANON.format(f"SELECT 2 * d.id AS a, 2 * b.id + 1 AS b FROM ({_GRAMS.format(id='doc_id', k=8, table='documents')}) d JOIN ({_GRAMS.format(id='item_id', k=8, table='benchmark')}) b USING (gram)")
EDGE_SQL["embedding_cos"] = """
WITH v AS (SELECT vec_id AS id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings WHERE embedding IS NOT NULL),
p AS (SELECT x.id AS src, y.id AS dst, list_inner_product(x.v, y.v)::HUGEINT AS d, list_inner_product(x.v, x.v)::HUGEINT * list_inner_product(y.v, y.v)::HUGEINT AS s FROM v x JOIN v y ON x.id < y.id)
SELECT src, dst, round(1 - d::DOUBLE / sqrt(s::DOUBLE), 6) AS w FROM p WHERE d > 0 AND 10000 * d * d >= 1600 * s"""


def cc_sql(edges: str, vertices: str | None = None) -> str:
    """(id, component) by label relaxation; ``vertices`` adds ids that no edge has."""
    start = f"SELECT id, id AS component FROM (SELECT DISTINCT id FROM nb{' UNION ' + vertices if vertices else ''})"
    return f"""WITH RECURSIVE e AS MATERIALIZED ({edges}), nb AS MATERIALIZED (SELECT src AS id, dst AS nbr FROM e UNION ALL SELECT dst, src FROM e),
cc(id, component) USING KEY (id) AS ({start} UNION
  SELECT nb.nbr, min(cc.component) FROM cc JOIN nb ON nb.id = cc.id JOIN recurring.cc AS old ON old.id = nb.nbr WHERE cc.component < old.component GROUP BY nb.nbr)"""


def _cc(edges: str, vertices: str | None = None) -> str:
    return cc_sql(edges, vertices) + " SELECT id, component FROM cc"


# -- shared inputs

_memo: dict[tuple, DataFrame] = {}


def _once(spark: SparkSession, key: tuple, make: Callable[[], DataFrame]) -> DataFrame:
    """A cut that queries of one session share."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _memo:
        _memo[key] = cut(make(), "shared")
    return _memo[key]


def _edges(spark: SparkSession, d: str, name: str) -> DataFrame:
    return _once(spark, ("edges", d, name), lambda: workloads.GRAPHS[name](spark, d))


def _graph(spark: SparkSession, d: str, name: str) -> Graph:
    return Graph(_edges(spark, d, name).select("src", "dst"))


def _comps(spark: SparkSession, d: str, name: str) -> DataFrame:
    return _once(spark, ("components", d, name), lambda: components.min_owner(_graph(spark, d, name)).components)


def _wedges(spark: SparkSession, d: str, name: str) -> DataFrame:
    if name == "order_gap":
        return _once(spark, ("wedges", d, name), lambda: workloads.order_gap(spark, d))
    return _edges(spark, d, name).select("src", "dst", "w")


ORDER_GAP_SQL = "SELECT least(a, b) AS src, greatest(a, b) AS dst, w FROM (SELECT o_orderkey AS a, lead(o_orderkey) OVER w AS b, CAST(date_diff('day', CAST(o_orderdate AS DATE), CAST(lead(o_orderdate) OVER w AS DATE)) AS DOUBLE) AS w FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)) WHERE b IS NOT NULL"

METHODS: dict[str, Callable[[Graph], object]] = {
    "neighbor_min": lambda g: components.neighbor_min(g),
    "neighbor_min_frontier": lambda g: components.neighbor_min(g, frontier=True),
    "all_members": lambda g: components.all_members(g, once=True),
    "min_owner": lambda g: components.min_owner(g),
    "min_owner_random": lambda g: components.min_owner(g, order="random"),
    "min_owner_retire": lambda g: components.min_owner(g, retire=True),
    "min_owner_precontract": lambda g: components.min_owner(g, precontract=True),
    "min_owner_sorted": lambda g: secondary_sort.min_owner_sorted(g),
    "min_owner_sorted_rdd": lambda g: secondary_sort.min_owner_sorted(g, backend="rdd"),
    "min_owner_balanced": lambda g: components.min_owner_balanced(g),
    "min_owner_balanced_50": lambda g: components.min_owner_balanced(g, tau=50),
    "upper_core": lambda g: components.upper_core(g),
    "upper_core_wide": lambda g: components.upper_core(g, repair="wide"),
    "hybrid_mode_switch": lambda g: components.hybrid_mode_switch(g, tau=100),
    "label_prop": lambda g: baselines.label_prop_baseline(g),
    "superstep": lambda g: baselines.superstep_min(g),
}
#: which graphs each method runs on as queries
RUNS = {m: ("doc_line",) for m in METHODS} | {
    "min_owner": ("order_chain_customer", "order_chain_global", "doc_line", "doc_exact", "event_chain", "customer_part_sparse", "embedding_cos", "part_tree", "conversation_chain", "part_supplier_sparse"),
    "all_members": ("doc_exact", "doc_jaccard"),
    "min_owner_balanced": ("customer_part", "part_supplier", "part_supplier_sparse", "doc_line"),
    "label_prop": ("doc_line", "customer_part"),
    "upper_core": ("doc_line", "customer_part_sparse"),
}


def _method(m: str, name: str) -> Query:
    return lambda spark, d: METHODS[m](_graph(spark, d, name)).components.select("id", "component")


def _global_chain(spark: SparkSession, d: str) -> DataFrame:
    """One path over all orders: stretches of time become stars before the first exchange."""
    edges = _once(spark, ("edges", d, "order_chain_dealt"), lambda: workloads.order_chain_dealt(spark, d))
    return components.min_owner(Graph(edges), precontract=True).components.select("id", "component")


def _page_links(spark: SparkSession, d: str) -> DataFrame:
    return builders.links(read_table(spark, d, "pages", ["page_id", "html"]))


def _members(spark: SparkSession, d: str) -> DataFrame:
    """Every component's members as one text, from all of its parts."""
    parts = measures.members(_comps(spark, d, "doc_exact")).select("component", "part", F.array_join(F.transform("members", lambda x: x.cast("string")), ",").alias("ids"))
    return parts.groupBy("component").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("part", "ids"))), lambda x: x["ids"]), ",").alias("members"))


def _isolated(spark: SparkSession, d: str) -> DataFrame:
    ids = read_table(spark, d, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("id"))
    return graphs.isolated(ids, _edges(spark, d, "order_chain_customer"))


def _with_isolated(spark: SparkSession, d: str) -> DataFrame:
    ids = read_table(spark, d, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("id"))
    return components.min_owner(Graph(_edges(spark, d, "part_supplier_sparse"), ids)).components


def _sevenths(spark: SparkSession, d: str) -> DataFrame:
    """A clustering that has nothing to do with the edges, for measures across clusters."""
    return read_table(spark, d, "documents", ["doc_id"]).select(F.col("doc_id").alias("id"), (F.col("doc_id") % 7).alias("component"))


def _st(spark: SparkSession, d: str) -> DataFrame:
    """s-t tests between the two least orders of a few customers."""
    g = _graph(spark, d, "doc_line")
    comps = _comps(spark, d, "doc_line")
    ends = comps.agg(F.min("id").alias("s"), F.max("id").alias("t"), F.min_by("id", F.struct("component", -F.col("id"))).alias("u")).first()
    rows = [(int(a), int(b), components.st_connected(g, a, b)) for a, b in ((ends["s"], ends["u"]), (ends["s"], ends["t"]))]
    return spark.createDataFrame(rows, "s long, t long, connected boolean")


def _asof(spark: SparkSession, d: str) -> DataFrame:
    """The chain that each event's user was in when it came: the last chain begun by then."""
    events = read_table(spark, d, "events", ["event_id", "ts", "user_id"])
    comps = _comps(spark, d, "event_chain")
    begun = events.join(comps, F.col("event_id") == F.col("id")).groupBy("user_id", "component").agg(F.min("ts").alias("since")).select("user_id", "since", F.col("component").alias("label"))
    return measures.label_asof(events, begun, "user_id", "ts").select("event_id", "user_id", "ts", "label")


def _streamed(spark: SparkSession, d: str) -> DataFrame:
    """Components of the event chains by micro-batches of an edge stream."""
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    _edges(spark, d, "event_chain").select("src", "dst").repartition(3).write.parquet(path)
    store = incremental.ComponentStore(spark)
    edges = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(path)
    incremental.components(edges, store).option("checkpointLocation", f"{path}-progress").trigger(availableNow=True).start().awaitTermination()
    drop_path(spark, path)
    drop_path(spark, f"{path}-progress")
    return store.labels


def _event_stream(spark: SparkSession, d: str) -> DataFrame:
    schema = read_table(spark, d, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d)


def _open_chain(spark: SparkSession, d: str) -> DataFrame:
    links = incremental.open_chain(_event_stream(spark, d), "event_id", "user_id", "ts", 6 * 3600)
    out = incremental.drain(links, f"chain_{abs(hash(d)):x}")
    return out.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))


def _session_stream(spark: SparkSession, d: str) -> DataFrame:
    return incremental.session_counts(read_table(spark, d, "events", ["ts", "user_id"]), "ts", "user_id", "6 hours")


def _windowed(spark: SparkSession, d: str) -> DataFrame:
    """Components of users and event types in each day's window."""
    events = read_table(spark, d, "events", ["ts", "user_id", "event_type", "value"])
    pairs = events.withColumn("a", F.col("user_id") * 2).withColumn("b", F.floor("value").cast("long") * 2 + 1)
    return incremental.windowed_graph(incremental.window_edges(pairs, "ts", "1 day", "a", "b"))


def _udtf(spark: SparkSession, d: str) -> DataFrame:
    """The table function on each customer's own graph."""
    sqlapi.register(spark)
    orders = read_table(spark, d, "orders", ["o_orderkey", "o_custkey"])
    _edges(spark, d, "order_chain_customer").join(orders, F.col("src") == F.col("o_orderkey")).createOrReplaceTempView("_customer_chains")
    return spark.sql("SELECT c.id, c.component FROM (SELECT o_custkey, collect_list(src) AS s, collect_list(dst) AS t FROM _customer_chains GROUP BY o_custkey) g, LATERAL components_of(g.s, g.t) c")


def _page_components(spark: SparkSession, d: str) -> DataFrame:
    """Components of pages and link targets: pages by id, each named by the least page of its component."""
    got = components.min_owner(_graph(spark, d, "page_link")).components
    pages = got.where("pmod(id, 2) = 0").select((F.col("id") / 2).cast("long").alias("page_id"), "component")
    least = pages.groupBy("component").agg(F.min("page_id").alias("first_page"))
    return pages.join(least, "component").select("page_id", "first_page")


def _table(name: str, make: Callable[[SparkSession, str], DataFrame], *columns: str) -> Query:
    """Columns of an experiment's table, which is run once a session."""
    return lambda spark, d: _once(spark, (name, d), lambda: make(spark, d)).select(*columns)


_RESULT = ("workload", "method", "v", "e", "largest", "n_components", "dnf")
_COST = ("rounds_run", "rounds_productive", "jobs", "peak_messages", "peak_state_rows", "seconds")
_BOUNDS = ("shape", "power", "v", "e", "d", "orders", "n_components", "rounds_within", "data_within")
#: sizes of the registered sweeps; ``workloads.sweep`` goes to 2^19
_POWERS = range(5, 15)
_SWEEPS = {s: (f"sweep_{s}", lambda spark, d, s=s: workloads.sweep(spark, s, _POWERS)) for s in ("path", "tree")}
_GROUPS = {k: (f"group{k}", lambda spark, d, g=g: workloads.compare(spark, d, g, repeats=1)) for k, g in ((1, workloads.GROUP_1), (2, workloads.GROUP_2))}
_SPARSE, _CLUSTERS, _CONTENDED = ("sparsify", workloads.sparsify), ("clustering", workloads.clustering), ("contention", workloads.contention)


def _udaf(spark: SparkSession, d: str) -> DataFrame:
    sqlapi.register(spark)
    orders = read_table(spark, d, "orders", ["o_orderkey", "o_custkey"])
    edges = _edges(spark, d, "order_chain_customer").join(orders, F.col("src") == F.col("o_orderkey")).createOrReplaceTempView("_chains")
    del edges
    return spark.sql("SELECT o_custkey, count_components(src, dst) AS n_components FROM _chains GROUP BY o_custkey")


def _agreement(spark: SparkSession, d: str) -> DataFrame:
    """How far shared lines and exact copies agree, over the documents that both have."""
    return measures.pair_agreement(_comps(spark, d, "doc_line"), _comps(spark, d, "doc_exact"))


def _sampled(spark: SparkSession, d: str) -> DataFrame:
    return graphs.sample_edges(_edges(spark, d, "part_supplier"), 10)


def _stats(run: Callable[[Graph], object], name: str) -> Query:
    return lambda spark, d: run(_graph(spark, d, name)).stats_frame(spark).drop("seconds")


def _generated(spark: SparkSession, d: str) -> DataFrame:
    """Edge counts of the shapes over the order keys."""
    ids = read_table(spark, d, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("id"))
    out = None
    for name, shape in generators.OVER.items():
        row = shape(ids).agg(F.lit(name).alias("shape"), F.count(F.lit(1)).alias("n_edges"))
        out = row if out is None else out.unionByName(row)
    return out


def _orders(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "orders", ["o_orderkey", "o_totalprice", "o_orderstatus", "o_orderpriority"])


_ORDERS, _DOCS = "order_chain_customer", "doc_line"


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {}
    for name in workloads.GRAPHS:
        if name != "page_link":
            out[f"edges_{name}"] = lambda spark, d, n=name: _edges(spark, d, n)
    out["edges_page_link"] = _page_links
    for m, names in RUNS.items():
        for name in names:
            out[f"cc_{m}_{name}"] = _method(m, name)
    out |= {
        "cc_min_owner_order_chain_global": _global_chain,
        "cc_min_owner_with_isolated": _with_isolated,
        "cc_sql_surface": lambda s, d: (sqlapi.register(s, d), sqlapi.components(s, "SELECT min(doc_id) OVER (PARTITION BY text) AS src, doc_id AS dst FROM documents"))[1],
        "cc_recursive_cte": lambda s, d: baselines.recursive_cte_components(_edges(s, d, "doc_exact"), 3),
        "isolated_orders": _isolated,
        "st_connected_doc_line": _st,
        "component_sizes": lambda s, d: measures.component_sizes(_comps(s, d, _ORDERS)),
        "size_histogram": lambda s, d: measures.size_histogram(_comps(s, d, _ORDERS)),
        "largest_k": lambda s, d: measures.topk(_comps(s, d, _ORDERS), 10),
        "rank_components": lambda s, d: measures.rank_components(_comps(s, d, _DOCS)),
        "degrees": lambda s, d: measures.degrees(_edges(s, d, "part_supplier")),
        "degree_histogram": lambda s, d: measures.degree_histogram(_edges(s, d, "customer_part")),
        "hubs": lambda s, d: measures.hubs(_edges(s, d, "part_supplier"), 10),
        "graph_profile": lambda s, d: measures.profile(_edges(s, d, _ORDERS), _comps(s, d, _ORDERS)),
        "approx_vertices": lambda s, d: measures.approx_vertices(_edges(s, d, "customer_part")),
        "component_members": _members,
        "component_summary": lambda s, d: measures.summarise(_orders(s, d), _comps(s, d, _ORDERS), "o_orderkey", "o_totalprice").withColumn("total", F.col("total").cast("double")),
        "rollup_component": lambda s, d: measures.rollup(read_table(s, d, "documents", ["doc_id", "lang", "source"]), _comps(s, d, _DOCS), "doc_id", "lang", "source").withColumn("level", F.col("level").cast("int")),
        "cube_component": lambda s, d: measures.cube(read_table(s, d, "documents", ["doc_id", "lang", "source"]), _comps(s, d, _DOCS), "doc_id", "lang", "source").withColumn("level", F.col("level").cast("int")),
        "attach_component": lambda s, d: measures.attach(read_table(s, d, "documents", ["doc_id", "lang"]), _comps(s, d, _DOCS), "doc_id"),
        "topk_within_component": lambda s, d: measures.topk_within(_orders(s, d), _comps(s, d, _ORDERS), "o_orderkey", "o_totalprice", 2),
        "rolling_activity": lambda s, d: measures.rolling(read_table(s, d, "events", ["event_id", "user_id", "ts"]).withColumn("sec", F.unix_seconds(F.col("ts").cast("timestamp"))), "user_id", "sec", 86_400).select("event_id", "n_recent"),
        "label_asof": _asof,
        "cut_edges": lambda s, d: measures.cut_edges(_edges(s, d, _DOCS), _sevenths(s, d)),
        "verify_components": lambda s, d: measures.verify(_graph(s, d, _DOCS), _comps(s, d, _DOCS)),
        "pair_agreement": _agreement,
        "clustering_diff": lambda s, d: measures.diff(_comps(s, d, _DOCS), _comps(s, d, "doc_exact")),
        "neighbor_min_rounds": lambda s, d: measures.minimum_rounds(_edges(s, d, _DOCS), _comps(s, d, _DOCS)),
        "bfs_from_least": lambda s, d: measures.bfs(_edges(s, d, _DOCS), _comps(s, d, _DOCS).select(F.col("component").alias("id")).distinct()),
        "induced_subgraph": lambda s, d: graphs.induced(_edges(s, d, "doc_line"), read_table(s, d, "labels", ["doc_id"]).select(F.col("doc_id").alias("id"))),
        "null_report": lambda s, d: graphs.null_report(_edges(s, d, "customer_part")),
        "union_edges": lambda s, d: graphs.union_edges(_edges(s, d, "doc_line"), _edges(s, d, "doc_exact")),
        "dictionary_collisions": lambda s, d: graphs.encode(_page_links(s, d), "href")[1],
        "relabel_rank": lambda s, d: graphs.relabel(_edges(s, d, "doc_exact"), "rank")[1].agg(F.count(F.lit(1)).alias("v"), F.min("rank").alias("lo"), F.max("rank").alias("hi"), F.countDistinct("rank").alias("n")),
        "sampled_edges": _sampled,
        "generated_shapes": _generated,
        "stats_min_owner": _stats(METHODS["min_owner"], _DOCS),
        "stats_min_owner_balanced": _stats(METHODS["min_owner_balanced_50"], "part_supplier_sparse"),
        "key_balance": lambda s, d: measures.balance(graphs.adjacency(_edges(s, d, "part_supplier")).withColumnRenamed("id", "key")),
        "minhash_pairs": lambda s, d: builders.minhash(read_table(s, d, "documents", ["doc_id", "text"]), "doc_id", "text"),
        "hyperplane_pairs": lambda s, d: builders.hyperplane_cosine(read_table(s, d, "embeddings", ["vec_id", "embedding"]), "vec_id", "embedding"),
        "cluster_distance": lambda s, d: linkage.cluster_distance(_sevenths(s, d), _wedges(s, d, "doc_jaccard")),
        "lighter_edges": lambda s, d: graphs.lighter(_wedges(s, d, "doc_jaccard"), 0.2),
        "slc_threshold_doc": lambda s, d: linkage.slc_threshold(_wedges(s, d, "doc_jaccard"), 0.2).components,
        "slc_threshold_order_gap": lambda s, d: linkage.slc_threshold(_wedges(s, d, "order_gap"), 60.0).components,
        "slc_rounds_min_owner_doc": lambda s, d: linkage.slc_rounds(_wedges(s, d, "doc_jaccard"), DistanceStop(0.2)).components,
        "slc_rounds_all_members_doc": lambda s, d: linkage.slc_rounds(_wedges(s, d, "doc_jaccard"), DistanceStop(0.2), hashing="all_members").components,
        "slc_rounds_embedding": lambda s, d: linkage.slc_rounds(_wedges(s, d, "embedding_cos"), DistanceStop(0.5)).components,
        "slc_dendrogram_cut_doc": lambda s, d: linkage.slc_dendrogram_cut(_wedges(s, d, "doc_jaccard"), DistanceStop(0.2)).components,
        "slc_size_rounds_doc": lambda s, d: linkage.slc_rounds(_wedges(s, d, "doc_jaccard"), SizeStop(3)).components,
        "slc_size_cut_doc": lambda s, d: linkage.slc_dendrogram_cut(_wedges(s, d, "doc_jaccard"), SizeStop(3)).components,
        "streaming_components": _streamed,
        "streaming_open_chain": _open_chain,
        "session_windows": _session_stream,
        "windowed_components": _windowed,
        "udtf_components": _udtf,
        "udaf_components": _udaf,
        "salted_attach": lambda s, d: measures.salted_join(read_table(s, d, "lineitem", ["l_orderkey", "l_linenumber", "l_suppkey"]), read_table(s, d, "supplier", ["s_suppkey", "s_nationkey"]).withColumnRenamed("s_suppkey", "l_suppkey"), "l_suppkey"),
        "component_percentiles": lambda s, d: measures.percentiles(_orders(s, d), _comps(s, d, _ORDERS), "o_orderkey", "o_totalprice"),
        "graph_density": lambda s, d: measures.density(measures.profile(_edges(s, d, _ORDERS), _comps(s, d, _ORDERS))).select("v", "e", F.round("density", 9).alias("density"), F.round("mean_degree", 6).alias("mean_degree")),
        "slc_rounds_retire_doc": lambda s, d: linkage.slc_rounds(_wedges(s, d, "doc_jaccard"), DistanceStop(0.2), retire=True).components,
        "cc_min_owner_page_link": _page_components,
        "workload_sparsify": _table(*_SPARSE, "workload", "percent", "e", "v", "largest", "n_components"),
        "workload_sparsify_cost": _table(*_SPARSE, "workload", "percent", "diameter", "rounds_run"),
        "workload_clustering": _table(*_CLUSTERS, "workload", "stop", "at", "hashing", "v", "largest", "n_clusters", "dnf"),
        "workload_clustering_cost": _table(*_CLUSTERS, "workload", "stop", "at", "hashing", "rounds_run", "seconds"),
        "workload_contention": _table(*_CONTENDED, "method", "k", "n_runs", "v", "largest", "n_components", "all_agree"),
        "workload_contention_times": _table(*_CONTENDED, "method", "k", "max_s", "median_s"),
    }
    for k, group in _GROUPS.items():
        out[f"workload_group{k}"] = _table(*group, *_RESULT)
        out[f"workload_group{k}_cost"] = _table(*group, "workload", "method", *_COST)
    for shape, swept in _SWEEPS.items():
        out[f"sweep_{shape}"] = _table(*swept, *_BOUNDS)
        out[f"sweep_{shape}_rounds"] = _table(*swept, "shape", "power", "worst_rounds", "rounds_run", "two_log_d", "mean_peak", "worst_peak")
    return out


def size_cut_sql(wedges: str, k: int) -> str:
    """(id, component) of the cut of the merge tree by size ``k``: an edge merges if its ends are not joined by lighter ones, and what these join to each end is smaller than ``k``."""
    return cc_sql("SELECT src, dst FROM accepted", "SELECT src FROM o UNION SELECT dst FROM o").replace(
        "WITH RECURSIVE ",
        f"""WITH RECURSIVE o AS MATERIALIZED (SELECT row_number() OVER (ORDER BY w, src, dst) AS r, src, dst FROM ({wedges})),
ob AS MATERIALIZED (SELECT r, src AS id, dst AS nbr FROM o UNION ALL SELECT r, dst, src FROM o),
reach(r, side, id) AS (SELECT r, side, id FROM (SELECT r, 0 AS side, src AS id FROM o UNION ALL SELECT r, 1, dst FROM o) UNION SELECT reach.r, side, nbr FROM reach JOIN ob ON ob.id = reach.id AND ob.r < reach.r),
sized AS MATERIALIZED (SELECT r, side, count(*) AS n FROM reach GROUP BY r, side),
closed AS MATERIALIZED (SELECT DISTINCT x.r FROM reach x JOIN reach y ON y.r = x.r AND y.id = x.id AND x.side = 0 AND y.side = 1),
accepted AS MATERIALIZED (SELECT src, dst FROM o WHERE r NOT IN (SELECT r FROM closed) AND r IN (SELECT r FROM sized GROUP BY r HAVING max(n) < {k})), """,
    )


def _sampled_sql(edges: str, percent: int) -> str:
    return f"SELECT src, dst FROM ({edges}) WHERE ('0x' || substr(md5('42:' || src || ':' || dst), 1, 8))::BIGINT % 10000 < {percent * 100}"


def _outcome_sql(cc: str, n: str = "n_components") -> str:
    return f"SELECT CAST(coalesce(sum(s), 0) AS BIGINT) AS v, coalesce(max(s), 0) AS largest, count(*) AS {n}, sum(s::HUGEINT * s * s) AS cubes FROM (SELECT component, count(*) AS s FROM ({cc}) GROUP BY component)"


def _experiments_sql() -> dict[str, str]:
    """Results of the experiments: what each run has to find, whatever its cost."""
    out = {}
    for k, (names, methods) in ((1, workloads.GROUP_1), (2, workloads.GROUP_2)):
        # all_members ends where its last round would send more than the cap: each member the whole component, from each member
        rows = [
            f"SELECT '{name}' AS workload, method, CASE WHEN NOT dnf THEN v END AS v, (SELECT count(*) FROM ({EDGE_SQL[name]})) AS e, CASE WHEN NOT dnf THEN largest END AS largest, CASE WHEN NOT dnf THEN n_components END AS n_components, dnf "
            f"FROM (SELECT *, method = 'all_members' AND cubes > {workloads.MEMBER_CAP} AS dnf FROM ({_outcome_sql(_cc(EDGE_SQL[name]))}), (SELECT unnest({list(methods)}) AS method))"
            for name in names
        ]
        out[f"workload_group{k}"] = " UNION ALL ".join(rows)
    rows = []
    for name in ("customer_part", "part_supplier"):
        for p in (50, 10, 5, 2, 1):
            part = _sampled_sql(EDGE_SQL[name], p)
            rows.append(f"SELECT '{name}' AS workload, {p} AS percent, (SELECT count(*) FROM ({part})) AS e, v, largest, n_components FROM ({_outcome_sql(_cc(part))})")
    out["workload_sparsify"] = " UNION ALL ".join(rows)
    rows = []
    for name in ("doc_jaccard", "embedding_cos"):
        own = EDGE_SQL[name]
        ids = f"SELECT src FROM ({own}) UNION SELECT dst FROM ({own})"
        for stop in workloads.STOPS:
            distance = isinstance(stop, DistanceStop)
            cut_ = _cc(f"SELECT src, dst FROM ({own}) WHERE w <= {stop.theta}", ids) if distance else size_cut_sql(own, stop.k) + " SELECT id, component FROM cc"
            kind, at = ("distance", stop.theta) if distance else ("size", stop.k)
            rows.append(f"SELECT '{name}' AS workload, '{kind}' AS stop, CAST({at} AS DOUBLE) AS at, hashing, v, largest, n_clusters, false AS dnf FROM ({_outcome_sql(cut_, 'n_clusters')}), (SELECT unnest(['min_owner', 'all_members']) AS hashing)")
    out["workload_clustering"] = " UNION ALL ".join(rows)
    out["workload_contention"] = f"SELECT method, k, k AS n_runs, v, largest, n_components, true AS all_agree FROM ({_outcome_sql(_cc(EDGE_SQL['doc_line']))}), (SELECT unnest({list(workloads.KS)}) AS k), (SELECT unnest(['min_owner', 'superstep']) AS method)"
    for shape, v, e, d in (("path", "n", "n - 1", "n - 1"), ("tree", "n - 1", "n - 2", "2 * (power - 1)")):
        out[f"sweep_{shape}"] = f"SELECT '{shape}' AS shape, power, {v} AS v, {e} AS e, {d} AS d, 10 AS orders, CAST(10 AS BIGINT) AS n_components, true AS rounds_within, true AS data_within FROM (SELECT CAST(power AS INTEGER) AS power, CAST(1 AS BIGINT) << CAST(power AS BIGINT) AS n FROM (SELECT unnest(range({_POWERS.start}, {_POWERS.stop})) AS power))"
    return out


def oracle_sql() -> dict[str, str]:
    out = {f"edges_{n}": q for n, q in EDGE_SQL.items()}
    out["edges_page_link"] = "SELECT DISTINCT page_id, href FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)"
    for m, names in RUNS.items():
        for name in names:
            # one path: its least id
            out[f"cc_{m}_{name}"] = "SELECT o_orderkey AS id, min(o_orderkey) OVER () AS component FROM orders" if name == "order_chain_global" else _cc(EDGE_SQL[name])
    orders, docs, exact = (cc_sql(EDGE_SQL[n]) for n in (_ORDERS, _DOCS, "doc_exact"))
    sizes = ", s AS (SELECT component, count(*) AS size FROM cc GROUP BY component)"
    two = ", " + cc_sql(EDGE_SQL["doc_exact"]).removeprefix("WITH RECURSIVE ").replace("recurring.cc", "recurring.xc").replace("cc", "xc").replace("nb", "xb").replace("e AS MATERIALIZED", "xe AS MATERIALIZED").replace("FROM e ", "FROM xe ").replace("FROM e)", "FROM xe)")
    bfs = docs + ", b(id, depth) USING KEY (id) AS (SELECT DISTINCT component AS id, 0 AS depth FROM cc UNION SELECT nb.nbr, min(b.depth) + 1 FROM b JOIN nb ON nb.id = b.id WHERE nb.nbr NOT IN (SELECT id FROM recurring.b) GROUP BY nb.nbr)"
    light = f"SELECT src, dst FROM ({JACCARD_SQL}) WHERE w <= 0.2"
    slc = _cc(light, f"SELECT src FROM ({JACCARD_SQL}) UNION SELECT dst FROM ({JACCARD_SQL})")
    cos = EDGE_SQL["embedding_cos"]
    level = "SELECT {g} AS level, lang, source, count(*) AS n_rows, count(DISTINCT component) AS n_components FROM cc JOIN documents ON doc_id = id GROUP BY {r}(lang, source)"
    # Spark numbers the bits from the left
    grouping = "CAST(grouping(lang) * 2 + grouping(source) AS INTEGER)"
    days = "SELECT DISTINCT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, user_id * 2 AS a, CAST(floor(value) AS BIGINT) * 2 + 1 AS b FROM events"
    out |= {
        "cc_min_owner_with_isolated": _cc(EDGE_SQL["part_supplier_sparse"], "SELECT o_orderkey FROM orders"),
        "cc_sql_surface": _cc(EDGE_SQL["doc_exact"], "SELECT doc_id FROM documents WHERE false"),
        "cc_recursive_cte": _cc(EDGE_SQL["doc_exact"]),
        "isolated_orders": f"WITH e AS ({EDGE_SQL[_ORDERS]}) SELECT o_orderkey AS id FROM orders WHERE o_orderkey NOT IN (SELECT src FROM e UNION SELECT dst FROM e)",
        "component_sizes": orders + sizes + " SELECT component, size FROM s",
        "size_histogram": orders + sizes + " SELECT size, count(*) AS n_components FROM s GROUP BY size",
        "largest_k": orders + sizes + " SELECT component, size FROM s ORDER BY size DESC, component LIMIT 10",
        "rank_components": docs + sizes + ", h AS (SELECT size, count(*) AS n_components FROM s GROUP BY size) SELECT size, n_components, CAST(sum(n_components) OVER w - n_components + 1 AS BIGINT) AS rank, CAST(sum(size * n_components) OVER w AS BIGINT) AS running_vertices FROM h WINDOW w AS (ORDER BY size DESC)",
        "degrees": f"WITH e AS ({EDGE_SQL['part_supplier']}) SELECT id, count(*) AS degree FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id",
        "degree_histogram": f"WITH e AS ({EDGE_SQL['customer_part']}) SELECT degree, count(*) AS n_vertices FROM (SELECT id, count(*) AS degree FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id) GROUP BY degree",
        "hubs": f"WITH e AS ({EDGE_SQL['part_supplier']}) SELECT id, count(*) AS degree FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id ORDER BY degree DESC, id LIMIT 10",
        "graph_profile": orders + sizes + ", d AS (SELECT id, count(*) AS g FROM nb GROUP BY id) SELECT (SELECT count(*) FROM cc) AS v, (SELECT count(*) FROM e) AS e, (SELECT max(size) FROM s) AS n, (SELECT count(*) FROM s) AS n_components, (SELECT max(g) FROM d) AS max_degree",
        "component_members": exact + " SELECT component, string_agg(CAST(id AS VARCHAR), ',' ORDER BY id) AS members FROM cc GROUP BY component",
        "component_summary": orders + " SELECT component, count(*) AS n_rows, CAST(sum(CAST(o_totalprice AS DECIMAL(18, 2))) AS DOUBLE) AS total, min(o_totalprice) AS least, max(o_totalprice) AS most, (max({'p': o_totalprice, 'k': o_orderkey})).k AS top_id, bool_and(o_totalprice > 0) AS all_positive FROM cc JOIN orders ON o_orderkey = id GROUP BY component",
        "rollup_component": docs + " " + level.format(g=grouping, r="ROLLUP "),
        "cube_component": docs + " " + level.format(g=grouping, r="CUBE "),
        "attach_component": docs + " SELECT doc_id, lang, component FROM documents LEFT JOIN cc ON id = doc_id",
        "topk_within_component": orders + " SELECT component, CAST(row_number() OVER w AS INTEGER) AS rank, o_orderkey, o_totalprice FROM cc JOIN orders ON o_orderkey = id WINDOW w AS (PARTITION BY component ORDER BY o_totalprice DESC, o_orderkey) QUALIFY row_number() OVER w <= 2",
        "rolling_activity": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n_recent FROM (SELECT event_id, user_id, CAST(floor(epoch_us(ts) / 1000000.0) AS BIGINT) AS s FROM events)",
        "label_asof": cc_sql(EDGE_SQL["event_chain"]) + ", l AS (SELECT user_id, component, min(ts) AS since FROM cc JOIN events ON event_id = id GROUP BY user_id, component) SELECT e.event_id, e.user_id, e.ts, l.component AS label FROM events e ASOF LEFT JOIN l ON l.user_id = e.user_id AND e.ts >= l.since",
        "cut_edges": f"SELECT src, dst, src % 7 AS c_src, dst % 7 AS c_dst FROM ({EDGE_SQL[_DOCS]}) WHERE src % 7 <> dst % 7",
        "st_connected_doc_line": docs + ", e2 AS (SELECT min(id) AS s, max(id) AS t, (SELECT id FROM cc ORDER BY component, id DESC LIMIT 1) AS u FROM cc), p AS (SELECT s, u AS t FROM e2 UNION ALL SELECT s, t FROM e2) SELECT s, t, a.component = b.component AS connected FROM p JOIN cc a ON a.id = s JOIN cc b ON b.id = t",
        "verify_components": "SELECT CAST(0 AS BIGINT) AS edges_across, CAST(0 AS BIGINT) AS wrong_names, CAST(0 AS BIGINT) AS ids_lost",
        "pair_agreement": docs + two + ", t AS (SELECT cc.component AS a, xc.component AS b, count(*) AS n FROM cc JOIN xc USING (id) GROUP BY 1, 2), p AS (SELECT (SELECT sum(n * (n - 1) // 2) FROM (SELECT sum(n) AS n FROM t GROUP BY a)) AS in_a, (SELECT sum(n * (n - 1) // 2) FROM (SELECT sum(n) AS n FROM t GROUP BY b)) AS in_b, (SELECT sum(n * (n - 1) // 2) FROM t) AS in_both, (SELECT sum(n) * (sum(n) - 1) // 2 FROM t) AS all_pairs) SELECT CAST(in_a AS BIGINT) AS in_a, CAST(in_b AS BIGINT) AS in_b, CAST(in_both AS BIGINT) AS in_both, CAST(all_pairs AS BIGINT) AS all_pairs, round(CASE WHEN in_a > 0 THEN in_both / in_a ELSE 1 END, 6) AS precision, round(CASE WHEN in_b > 0 THEN in_both / in_b ELSE 1 END, 6) AS recall, round((all_pairs - in_a - in_b + 2 * in_both) / all_pairs, 6) AS rand_index FROM p",
        "clustering_diff": docs + two + " SELECT id, component, 'a' AS side FROM (SELECT id, component FROM cc EXCEPT SELECT id, component FROM xc) UNION ALL SELECT id, component, 'b' FROM (SELECT id, component FROM xc EXCEPT SELECT id, component FROM cc)",
        "neighbor_min_rounds": bfs + " SELECT max(depth) AS rounds FROM b",
        "bfs_from_least": bfs + " SELECT id, depth FROM b",
        "induced_subgraph": f"SELECT src, dst FROM ({EDGE_SQL[_DOCS]}) WHERE src IN (SELECT doc_id FROM labels) AND dst IN (SELECT doc_id FROM labels)",
        "null_report": f"SELECT count(*) AS n_rows, CAST(0 AS BIGINT) AS n_null, CAST(0 AS BIGINT) AS n_loops FROM ({EDGE_SQL['customer_part']})",
        "union_edges": f"{EDGE_SQL[_DOCS]} UNION {EDGE_SQL['doc_exact']}",
        "dictionary_collisions": "SELECT CAST(0 AS BIGINT) AS id, CAST(0 AS BIGINT) AS n WHERE false",
        "relabel_rank": f"WITH e AS ({EDGE_SQL['doc_exact']}), v AS (SELECT count(*) AS v FROM (SELECT src FROM e UNION SELECT dst FROM e)) SELECT v, CAST(0 AS BIGINT) AS lo, v - 1 AS hi, v AS n FROM v",
        "generated_shapes": "WITH o AS (SELECT DISTINCT o_orderkey AS id FROM orders WHERE o_orderkey IS NOT NULL), p AS (SELECT x.id FROM o x JOIN o y ON y.id = x.id + 1), m AS (SELECT count(*) AS n FROM o) SELECT 'path' AS shape, count(*) AS n_edges FROM p UNION ALL SELECT 'cycle', count(*) + (SELECT CASE WHEN n > 2 THEN 1 ELSE 0 END FROM m) FROM p UNION ALL SELECT 'tree', count(*) FROM o x JOIN o y ON y.id = x.id // 2 WHERE x.id >= 2 UNION ALL SELECT 'star', greatest(n - 1, 0) FROM m UNION ALL SELECT 'clique', CAST(coalesce(sum(n * (n - 1) // 2), 0) AS BIGINT) FROM (SELECT count(*) AS n FROM o GROUP BY id // 10) UNION ALL SELECT 'grid', (SELECT count(*) FROM p WHERE id % 30 <> 29) + (SELECT count(*) FROM o x JOIN o y ON y.id = x.id + 30)",
        "cluster_distance": f"SELECT c1, c2, x.w AS w, x.src AS src, x.dst AS dst FROM (SELECT least(src % 7, dst % 7) AS c1, greatest(src % 7, dst % 7) AS c2, min({{'w': w, 'src': src, 'dst': dst}}) AS x FROM ({JACCARD_SQL}) WHERE src % 7 <> dst % 7 GROUP BY 1, 2)",
        "lighter_edges": f"SELECT src, dst, w FROM ({JACCARD_SQL}) WHERE w <= 0.2",
        "slc_threshold_doc": slc,
        "slc_threshold_order_gap": _cc(f"SELECT src, dst FROM ({ORDER_GAP_SQL}) WHERE w <= 60", f"SELECT src FROM ({ORDER_GAP_SQL}) UNION SELECT dst FROM ({ORDER_GAP_SQL})"),
        "slc_rounds_min_owner_doc": slc,
        "slc_rounds_all_members_doc": slc,
        "slc_rounds_retire_doc": slc,
        "salted_attach": "SELECT l_suppkey, l_orderkey, l_linenumber, s_nationkey FROM lineitem JOIN supplier ON s_suppkey = l_suppkey",
        "component_percentiles": orders + " SELECT component, quantile_disc(o_totalprice, 0.25) AS p25, quantile_disc(o_totalprice, 0.5) AS p50, quantile_disc(o_totalprice, 0.75) AS p75 FROM cc JOIN orders ON o_orderkey = id GROUP BY component",
        "graph_density": orders + ", c AS (SELECT (SELECT count(*) FROM cc) AS v, (SELECT count(*) FROM e) AS e) SELECT v, e, round(2 * e / (v * (v - 1)), 9) AS density, round(2 * e / v, 6) AS mean_degree FROM c",
        "slc_dendrogram_cut_doc": slc,
        "slc_rounds_embedding": _cc(f"SELECT src, dst FROM ({cos}) WHERE w <= 0.5", f"SELECT src FROM ({cos}) UNION SELECT dst FROM ({cos})"),
        "streaming_components": _cc(EDGE_SQL["event_chain"]),
        "streaming_open_chain": EDGE_SQL["event_chain"],
        "session_windows": 'WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), n AS (SELECT user_id, ts, sum(first) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS "end", count(*) AS n FROM n GROUP BY user_id, k',
        "windowed_components": f"WITH RECURSIVE d AS MATERIALIZED ({days}), nb AS MATERIALIZED (SELECT start, a AS id, b AS nbr FROM d UNION ALL SELECT start, b, a FROM d), cc(start, id, component) USING KEY (start, id) AS (SELECT DISTINCT start, id, id AS component FROM nb UNION SELECT nb.start, nb.nbr, min(cc.component) FROM cc JOIN nb ON nb.id = cc.id AND nb.start = cc.start JOIN recurring.cc AS old ON old.id = nb.nbr AND old.start = nb.start WHERE cc.component < old.component GROUP BY nb.start, nb.nbr) SELECT start, id, component FROM cc",
        "udaf_components": f"SELECT o_custkey, CAST(1 AS BIGINT) AS n_components FROM ({EDGE_SQL[_ORDERS]}) JOIN orders ON o_orderkey = src GROUP BY o_custkey",
        "udtf_components": _cc(EDGE_SQL[_ORDERS]),
        "sampled_edges": _sampled_sql(EDGE_SQL["part_supplier"], 10),
        "slc_size_rounds_doc": size_cut_sql(JACCARD_SQL, 3) + " SELECT id, component FROM cc",
        "slc_size_cut_doc": size_cut_sql(JACCARD_SQL, 3) + " SELECT id, component FROM cc",
        "cc_min_owner_page_link": "WITH RECURSIVE l AS MATERIALIZED (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages), nb AS MATERIALIZED (SELECT DISTINCT x.page_id AS id, y.page_id AS nbr FROM l x JOIN l y USING (href)), cc(id, component) USING KEY (id) AS (SELECT DISTINCT id, id AS component FROM nb UNION SELECT nb.nbr, min(cc.component) FROM cc JOIN nb ON nb.id = cc.id JOIN recurring.cc AS old ON old.id = nb.nbr WHERE cc.component < old.component GROUP BY nb.nbr) SELECT id AS page_id, component AS first_page FROM cc",
    }
    return out | _experiments_sql()
