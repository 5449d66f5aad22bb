"""Sources, sinks, measures, streaming, claims about rounds and exchange."""

import math
import os

import pytest

from componentry import schemas, sqlapi
from componentry.functions import graphs
from componentry.functions.graphs import graph
from componentry.operators import components, measures
from componentry.queries import queries
from componentry.sources import builders, generators, io
from componentry.streaming import incremental


def test_edge_files(spark, tmp_path):
    edges = spark.createDataFrame([(1, 2), (3, 4)], "src long, dst long")
    for fmt in ("parquet", "orc", "json"):
        io.write_edges(edges, f"{tmp_path}/{fmt}", fmt)
        assert sorted(map(tuple, io.read_edges(spark, f"{tmp_path}/{fmt}", fmt).collect())) == [(1, 2), (3, 4)]
    (tmp_path / "e.tsv").write_text("# comment\n1\t2\n3\t4\n")
    assert io.read_edge_text(spark, str(tmp_path / "e.tsv")).count() == 2
    lists = spark.createDataFrame([(1, [2, 3]), (4, [])], "id long, nbrs array<long>")
    assert sorted(map(tuple, io.read_adjacency(lists).collect())) == [(1, 2), (1, 3), (4, 4)]
    with pytest.raises(schemas.SchemaError):
        io.write_edges(edges.withColumnRenamed("src", "x"), f"{tmp_path}/no")


def test_sinks_and_restart(spark, tmp_path):
    comps = components.min_owner(graph(generators.path(spark, 6))).components
    io.write_components(comps, f"{tmp_path}/c", parts=2)
    assert spark.read.parquet(f"{tmp_path}/c").count() == 6
    io.write_components(comps, table="bucketed_components", buckets=4, mode="overwrite")
    assert spark.table("bucketed_components").count() == 6
    store = io.RoundStore(spark, "t", f"{tmp_path}")
    for r in range(4):
        store.save(r, comps)
    assert store.rounds() == [2, 3] and store.load(3).count() == 6


def test_validation(spark):
    bad = spark.createDataFrame([(1, None)], "src long, dst long")
    with pytest.raises(Exception, match="null id in dst"):
        graphs.validate(bad).collect()
    assert graph(bad).edges.count() == 0


def test_relabel_is_a_bijection(spark):
    edges = generators.path(spark, 3000)
    mixed, book = graphs.relabel(edges, "mix", 3)
    assert book.select("rank").distinct().count() == 3000 and mixed.count() == 2999
    ranked, book = graphs.relabel(edges, "rank", 3)
    assert sorted(r[0] for r in book.select("rank").collect()) == list(range(3000)) and ranked.count() == 2999


@pytest.mark.parametrize("shape", ["path", "tree"])
def test_rounds_and_data_stay_within_bounds(spark, shape):
    n = 128
    edges = generators.path(spark, n) if shape == "path" else generators.tree(spark, n - 1)
    v, e, d = (n, n - 1, n - 1) if shape == "path" else (n - 1, n - 2, 12)
    for seed in range(2):
        got = measures.exchange(components.min_owner(graph(edges), order="random", seed=seed), v, e)
        limit = measures.bounds(n, d)
        assert got["rounds_productive"] <= max(limit["2log2_d"], 4 * math.log2(d))
        assert got["rounds_productive"] <= limit["4log2_n"]
        assert got["state_ratio"] <= 3
    core = components.upper_core(graph(edges), order="random", seed=1)
    assert core.rounds_run <= 3 * math.log2(n) + 6


def test_neighbor_min_takes_as_many_rounds_as_hops(spark):
    edges = generators.path(spark, 12)
    run = components.neighbor_min(graph(edges))
    assert run.rounds_productive == measures.minimum_rounds(edges, run.components).first()[0] == 11
    assert components.min_owner(graph(edges)).rounds_productive < 11


def test_diameter_and_verify(spark):
    edges = generators.grid(spark, 3, 4)
    assert measures.diameter(edges, "exact") == 5
    assert measures.diameter(generators.path(spark, 9)) == 8
    g = graph(edges)
    assert tuple(measures.verify(g, components.min_owner(g).components).first()) == (0, 0, 0)


def test_stream_in_any_batches(spark):
    edges = [(i, (i * 7 + 3) % 90) for i in range(60)]
    want = {r[0]: r[1] for r in components.min_owner(graph(spark.createDataFrame(edges, "src long, dst long"))).components.collect()}
    for cuts in ([20, 40], [1, 59]):
        store = incremental.ComponentStore(spark)
        parts = [edges[a:b] for a, b in zip([0, *cuts], [*cuts, 60])]
        for k, part in enumerate(parts):
            store.add(spark.createDataFrame(part, "src long, dst long"), k)
        store.add(spark.createDataFrame([(0, 1)], "src long, dst long"), 0)  # given again: no effect
        assert {r[0]: r[1] for r in store.labels.collect()} == want


def test_store_goes_on_after_a_restart(spark, tmp_path):
    edges = [(1, 2), (3, 4), (2, 3), (8, 9)]
    first = incremental.ComponentStore(spark, f"{tmp_path}/labels")
    for k, e in enumerate(edges[:2]):
        first.add(spark.createDataFrame([e], "src long, dst long"), k)
    # a generation that was not written to its end does not count
    (tmp_path / "labels" / "batch=000000000009").mkdir()
    again = incremental.ComponentStore(spark, f"{tmp_path}/labels")
    assert again.batch == 1
    again.add(spark.createDataFrame([(1, 4)], "src long, dst long"), 1)  # given again: no effect
    for k, e in enumerate(edges[2:], 2):
        again.add(spark.createDataFrame([e], "src long, dst long"), k)
    assert dict(map(tuple, again.labels.collect())) == {1: 1, 2: 1, 3: 1, 4: 1, 8: 8, 9: 8}
    assert incremental.ComponentStore(spark, f"{tmp_path}/labels").labels.count() == 6


def test_edges_once_within_the_watermark(spark, tmp_path):
    rows = [("2024-01-01 00:00:00", 1, 2), ("2024-01-01 00:10:00", 1, 2), ("2024-01-01 00:20:00", 3, 4), ("2024-01-01 00:20:00", 2, 1)]
    spark.createDataFrame(rows, "ts string, src long, dst long").selectExpr("cast(ts as timestamp) ts", "src", "dst").write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("ts timestamp, src long, dst long").parquet(f"{tmp_path}/in")
    out = incremental.drain(incremental.distinct_edges(stream, "ts"), "once_edges")
    assert sorted((r["src"], r["dst"]) for r in out.collect()) == [(1, 2), (2, 1), (3, 4)]


def test_late_edges_are_dropped_beyond_the_watermark(spark, tmp_path):
    # a watermark takes effect on late rows one batch after the batch that moved it
    rows = [[("2024-01-01 00:10:00", 1, 2)], [("2024-01-01 09:00:00", 3, 4)], [("2024-01-01 09:10:00", 3, 4)], [("2024-01-01 00:20:00", 5, 6), ("2024-01-01 08:30:00", 7, 8)], [("2024-01-02 09:00:00", 9, 9)]]
    schema = "ts timestamp, src long, dst long"
    for i, part in enumerate(rows):
        spark.createDataFrame(part, "ts string, src long, dst long").selectExpr("cast(ts as timestamp) ts", "src", "dst").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in/{i}")
        for f in (tmp_path / "in" / str(i)).glob("*.parquet"):
            os.utime(f, (1_700_000_000 + 100 * i,) * 2)  # files are read in this order
    stream = spark.readStream.schema(schema).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    out = incremental.drain(incremental.window_edges(stream, "ts", "1 hour", "src", "dst", late="1 hour"), "late_edges", "update")
    seen = {(r["src"], r["dst"]) for r in out.collect()}
    assert {(1, 2), (3, 4), (7, 8)} <= seen and (5, 6) not in seen


def test_sql_functions(spark):
    sqlapi.register(spark)
    rows = spark.sql("SELECT * FROM components_of(array(1L, 2L, 7L), array(2L, 3L, 8L))").collect()
    assert {r[0]: r[1] for r in rows} == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7}


def test_large_groups_become_a_star(spark):
    df = spark.range(500).selectExpr("id", "1 as k", "'text' as t", "cast(null as string) as none")
    assert builders.share_key(df, "id", "k").count() == builders.share_key(df, "id", "k", "t").count() == 499
    assert builders.share_key(df, "id", "k", "none").count() == 0


def test_recall_of_the_hashed_joins(spark):
    """Pairs that hashing finds, of those that the exact joins find, on the given tables."""
    d = "/root/testdata/sf0.01"
    docs, vectors = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/embeddings.parquet")
    exact = builders.jaccard(docs, "doc_id", "text").select("src", "dst")
    assert exact.intersect(builders.minhash(docs, "doc_id", "text")).count() >= 0.9 * exact.count() > 50
    near = builders.cosine(vectors, "vec_id", "embedding").select("src", "dst")
    assert near.intersect(builders.hyperplane_cosine(vectors, "vec_id", "embedding")).count() >= 0.9 * near.count() > 30
    # columns that nothing asks for may be left out
    assert builders.cosine(vectors, "vec_id", "embedding").count() == near.count() == near.distinct().count()


def test_chain_without_parts(spark):
    before = builders.CHAIN_ROWS
    builders.CHAIN_ROWS = 10
    try:
        for kind in ("long", "timestamp"):
            df = spark.range(95).selectExpr("id", f"cast(id * id div 7 as {kind}) as at")
            assert sorted(map(tuple, builders.chain(df, "id", ["at", "id"]).collect())) == [(i, i + 1) for i in range(94)]
        assert builders.chain(df.limit(0), "id", ["at", "id"]).count() == 0
    finally:
        builders.CHAIN_ROWS = before


def test_job_counts_and_experiments(spark, tmp_path):
    from componentry import workloads

    run, jobs = measures.job_count(spark, lambda: components.min_owner(graph(generators.path(spark, 6))))
    assert jobs >= run.rounds_run
    rows = {(r["shape"], r["power"]): r for r in workloads.sweep(spark, "path", range(4, 6), 3).collect()}
    assert all(r["rounds_within"] and r["data_within"] and r["n_components"] == 3 for r in rows.values())
    alone = [measures.exchange(components.min_owner(graph(generators.path(spark, 16)), order="random", seed=k), 16, 15)["rounds_productive"] for k in range(3)]
    assert abs(rows["path", 4]["worst_rounds"] - max(alone)) <= 3


def test_advisor():
    assert components.choose_method({"n": 5, "v": 100, "e": 100})[0] == "all_members"
    assert components.choose_method({"n": 10**7, "v": 10**8, "e": 10**9})[0] == "min_owner_balanced"
    assert components.choose_method({"n": 5000, "v": 10**5, "e": 10**6})[0] == "min_owner"


def test_members_of_components_over_the_cap(spark):
    comps = spark.range(-1500, 1700).selectExpr("id", "-1500L as component").unionByName(spark.createDataFrame([(5000, 5000), (9000, 5000)], "id long, component long"))
    rows = measures.members(comps, cap=1000).orderBy("component", "part").collect()
    assert [i for r in rows if r["component"] == -1500 for i in r["members"]] == list(range(-1500, 1700))
    assert all(len(r["members"]) <= 1000 for r in rows) and [r["members"] for r in rows if r["component"] == 5000] == [[5000, 9000]]


def test_component_members_query_returns_large_groups(spark, tmp_path):
    spark.range(2500).selectExpr("id as doc_id", "'the same text' as text").write.parquet(f"{tmp_path}/documents.parquet")
    rows = queries()["component_members"](spark, str(tmp_path)).collect()
    assert [r["members"] for r in rows] == [",".join(map(str, range(2500)))]


def test_a_line_of_many_documents_links_them_all(spark, tmp_path):
    spark.range(60).selectExpr("id as doc_id", "concat('own words ', id, '\n', repeat('a shared line ', 4)) as text").write.parquet(f"{tmp_path}/documents.parquet")
    assert queries()["edges_doc_line"](spark, str(tmp_path)).count() == 59
    assert queries()["cc_min_owner_doc_line"](spark, str(tmp_path)).select("component").distinct().count() == 1


def test_jaccard_whole_has_large_groups_and_late_words(spark, tmp_path):
    head = " ".join(f"h{i}" for i in range(400))
    rows = [(i, "one text that sixty documents hold") for i in range(60)]
    rows += [(100, head + " " + " ".join(f"a{i}" for i in range(900))), (101, head + " " + " ".join(f"b{i}" for i in range(900))), (102, "x " + " ".join(f"a{i}" for i in range(900)))]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r["src"], r["dst"]): r["w"] for r in queries()["edges_doc_jaccard"](spark, str(tmp_path)).collect()}
    assert {p for p in got if p[1] < 100} == {(0, j) for j in range(1, 60)} and got[0, 59] == 0
    # 100 and 101 are alike in their first 400 words only; 100 and 102 in what follows
    assert {p for p in got if p[1] >= 100} == {(100, 102)}


def test_shapes_are_read_from_a_table(spark, tmp_path):
    """Keys with a gap: 0 to 39 and 60 to 99."""
    spark.range(100).where("id < 40 or id >= 60").withColumnRenamed("id", "o_orderkey").write.parquet(f"{tmp_path}/orders.parquet")
    got = dict(map(tuple, queries()["generated_shapes"](spark, str(tmp_path)).collect()))
    assert got == {"path": 78, "tree": 38 + 20, "star": 79, "cycle": 79, "clique": 8 * 45, "grid": 78 - 2 + 30}


def test_dealt_chain_is_contracted(spark, tmp_path):
    """The edges of a stretch of time lie side by side, so blocks of them become few stars: far fewer rounds than a path takes."""
    from componentry import workloads

    spark.range(5000).selectExpr("pmod(id * 2311, 5000) as o_orderkey", "cast(date'2020-01-01' + cast(id div 10 as int) as date) as o_orderdate").write.parquet(f"{tmp_path}/orders.parquet")
    edges = workloads.order_chain_dealt(spark, str(tmp_path))
    whole = workloads.order_chain_global(spark, str(tmp_path))
    assert edges.count() == whole.count() == 4999 and edges.exceptAll(whole).isEmpty()
    run = components.min_owner(graph(edges), precontract=True)
    assert run.rounds_run <= 6 < components.min_owner(graph(whole)).rounds_run
    assert run.components.where("component = 0").count() == 5000


def test_hyperplane_copies_stay_linear(spark):
    """300 equal vectors are a star, not all pairs; a bucket cut into parts finds what a whole one does."""
    rows = [(i, [1.0 if k == 0 else 0.0 for k in range(64)]) for i in range(300)] + [(300 + i, [1.0 if k == 0 else 0.01 * (i + 1) if k == i + 1 else 0.0 for k in range(64)]) for i in range(40)]
    df = spark.createDataFrame(rows, "id long, v array<float>")
    got = {tuple(r) for r in builders.hyperplane_cosine(df, "id", "v").collect()}
    assert {p for p in got if p[1] < 300} == {(0, i) for i in range(1, 300)} and len(got) < 300 + 41 * 41
    before = builders.BUCKET_ROWS
    builders.BUCKET_ROWS = 7
    try:
        assert {tuple(r) for r in builders.hyperplane_cosine(df, "id", "v").collect()} == got
    finally:
        builders.BUCKET_ROWS = before


def test_pages_of_a_large_block(spark, monkeypatch):
    """One family of near copies, joined whole and in pages: the same pairs, each once; copies by their class."""
    from componentry.operators import sets

    rows = [(i, " ".join(f"w{k}" for k in range(i, i + 40))) for i in range(60)] + [(100 + i, " ".join(f"w{k}" for k in range(i, i + 40))) for i in range(5)]
    df = spark.createDataFrame(rows, "id long, text string")
    want = {(i, j) for i in range(60) for j in range(i + 1, 60) if 2 * (38 - (j - i)) >= 38 + (j - i)} | {(i, 100 + i) for i in range(5)}
    for sets_of_page, shingles in ((1024, 1_000_000), (7, 1_000_000), (1024, 200)):
        monkeypatch.setattr(sets, "PAGE_SETS", sets_of_page)
        monkeypatch.setattr(sets, "PAGE_SHINGLES", shingles)
        got = [(r["src"], r["dst"]) for r in builders.jaccard(df, "id", "text").collect()]
        assert len(got) == len(set(got)) and set(got) == want
    assert {tuple(r) for r in builders.minhash(df, "id", "text").collect()} <= want


def test_sweeps_stay_in_the_component(spark, monkeypatch):
    """Both sweeps in one task, or by joins over the edges of the component alone: the same number, and other components are not read."""
    edges = [(0, 1), (1, 2), (2, 3), (3, 4), (2, 9), (9, 10), (10, 11), (11, 12)] + [(100 + i, 101 + i) for i in range(40)]
    df = spark.createDataFrame(edges, "src long, dst long")
    comps = components.min_owner(graph(df)).components
    calls, real = [], measures.bfs
    monkeypatch.setattr(measures, "bfs", lambda e, s: calls.append(e.count()) or real(e, s))
    assert measures.diameter(df, components=comps) == 6 and calls == []
    monkeypatch.setattr(measures, "SWEEP_EDGES", 3)
    assert measures.diameter(df, components=comps) == 6 and calls == [8, 8]
    assert measures.diameter(df.limit(0), components=comps) == 0


def test_samples_are_taken_from_larger_ones(spark, monkeypatch):
    """A graph's edges are digested once, not for each share; the shares are those of the whole, in any order."""
    from componentry import workloads
    from componentry.functions.graphs import sample_edges

    whole = spark.range(400).selectExpr("id as src", "1000 + id % 7 as dst")
    read = []
    monkeypatch.setitem(workloads.GRAPHS, "customer_part", lambda s, d: whole)
    monkeypatch.setattr(workloads, "sample_edges", lambda e, p: read.append(e.count()) or sample_edges(e, p))
    got = {r["percent"]: r["e"] for r in workloads.sparsify(spark, "", ("customer_part",), (5, 50, 20)).collect()}
    assert got == {p: sample_edges(whole, p).count() for p in (50, 20, 5)}
    assert read == [400, got[50], got[20]]
