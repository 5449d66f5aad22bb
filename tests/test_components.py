"""Every component method against union-find, over awkward graphs."""

import random

import pytest

from componentry.functions.graphs import graph
from componentry.operators import baselines, components, secondary_sort
from componentry.plans.rounds import NotConverged
from componentry.queries import queries


def union_find(edges, ids=()):
    up = {}

    def find(x):
        up.setdefault(x, x)
        while up[x] != x:
            x = up[x]
        return x

    for i in ids:
        find(i)
    for a, b in edges:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {i: find(i) for i in up}


def shuffled_path(n, seed):
    ids = list(range(n))
    random.Random(seed).shuffle(ids)
    return list(zip(ids, ids[1:]))


SHAPES = {
    "mixed": [(1, 2), (2, 1), (2, 3), (5, 5), (7, 8), (-4, 9), (2**60, 10), (10, -4)],
    "path": shuffled_path(18, 3),
    "star": [(0, i) for i in range(1, 60)] + [(100, i) for i in range(101, 110)],
    "random": [(random.Random(5).randrange(80), random.Random(i).randrange(80)) for i in range(60)],
}

RUNS = {
    "neighbor_min": lambda g: components.neighbor_min(g),
    "neighbor_min_frontier": lambda g: components.neighbor_min(g, frontier=True),
    "all_members": lambda g: components.all_members(g),
    "min_owner": lambda g: components.min_owner(g),
    "min_owner_random": lambda g: components.min_owner(g, order="random", seed=7, detect="exact"),
    "min_owner_retire": lambda g: components.min_owner(g, retire=True),
    "min_owner_contracted": lambda g: components.min_owner(g, precontract=True),
    "sorted": lambda g: secondary_sort.min_owner_sorted(g),
    "sorted_rdd": lambda g: secondary_sort.min_owner_sorted(g, backend="rdd"),
    "balanced_3": lambda g: components.min_owner_balanced(g, tau=3),
    "balanced_1": lambda g: components.min_owner_balanced(g, tau=1),
    "balanced_inf": lambda g: components.min_owner_balanced(g, tau=None),
    "upper_core": lambda g: components.upper_core(g),
    "upper_core_wide": lambda g: components.upper_core(g, repair="wide"),
    "hybrid": lambda g: components.hybrid_mode_switch(g, tau=4),
    "label_prop": lambda g: baselines.label_prop_baseline(g),
    "superstep": lambda g: baselines.superstep_min(g),
}


@pytest.mark.parametrize("name", RUNS)
def test_exact_partition(spark, name):
    # all shapes side by side in one graph, with ids that no edge has
    edges = [(a + k * 10_000, b + k * 10_000) for k, own in enumerate(SHAPES.values()) for a, b in own]
    ids = [-1000, 5, 77_777]
    g = graph(spark.createDataFrame(edges, "src long, dst long"), spark.createDataFrame([(i,) for i in {*ids, *(x for e in edges for x in e)}], "id long"))
    assert dict(map(tuple, RUNS[name](g).components.collect())) == union_find(edges, ids)


def test_contraction_joins_what_the_edges_join(spark):
    from componentry.operators.contract import forest_edges, star_edges

    r = random.Random(6)
    edges = [(r.randrange(300) - 50, r.randrange(300) - 50) for _ in range(260)]
    df = spark.createDataFrame(edges, "src long, dst long").repartition(3)
    pairs = spark.createDataFrame([((0, a), (0, b)) for a, b in edges], "src struct<k: int, i: long>, dst struct<k: int, i: long>")
    for shrink in (star_edges, forest_edges):
        for rows in (10, 1000):
            got = [tuple(x) for x in shrink(df, rows).collect()]
            assert union_find(got, {x for e in edges for x in e}) == union_find(edges)
            if shrink is star_edges:
                assert all(a < b for a, b in got)
        assert union_find([(a["i"], b["i"]) for a, b in shrink(pairs).collect()], {x for e in edges for x in e}) == union_find(edges)


def test_empty(spark):
    g = graph(spark.createDataFrame([], "src long, dst long"))
    for f in (components.min_owner, components.neighbor_min, components.all_members, components.min_owner_balanced, components.upper_core):
        assert f(g).components.count() == 0


def test_member_cap_is_dnf(spark):
    g = graph(spark.createDataFrame([(0, i) for i in range(1, 200)], "src long, dst long"))
    with pytest.raises(NotConverged):
        components.all_members(g, member_cap=1000)
    with pytest.raises(NotConverged):
        components.neighbor_min(graph(spark.createDataFrame([(i, i + 1) for i in range(30)], "src long, dst long")), max_rounds=5)


def test_st_connected(spark):
    g = graph(spark.createDataFrame([(1, 2), (2, 3), (8, 9)], "src long, dst long"))
    assert components.st_connected(g, 1, 3)
    assert not components.st_connected(g, 1, 9)
    assert components.st_connected(g, 9, 9)
    assert not components.st_connected(g, 1, 4444)


def test_one_exchange_a_round(spark):
    from componentry.operators import emit

    state = spark.range(100).selectExpr("id as key", "id as member", "id as owner")
    plan = emit.merge_union(emit.min_owner(state))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Python" not in plan


def test_owner_rounds_of_the_worked_example(spark):
    """Keys 1 and 5 hold {1,2,4} and {3,4,5}: the owner has all five ids after the third round, a star stays after the fourth."""
    from componentry.operators import emit

    def rows(state):
        out = {}
        for k, m in state.select("key", "member").collect():
            out.setdefault(k, set()).add(m)
        return out

    state = emit.with_owner(spark.createDataFrame([(1, 1), (1, 2), (1, 4), (5, 3), (5, 4), (5, 5)], "key long, member long"))
    seen = []
    for _ in range(5):
        state = emit.merge_union(emit.min_owner(state))
        seen.append(rows(state))
    assert seen[0][4] == {1, 3}
    assert seen[1][3] == {1, 3, 4, 5}
    assert seen[2][1] == {1, 2, 3, 4, 5}
    assert seen[3] == {1: {1, 2, 3, 4, 5}, 2: {1}, 3: {1}, 4: {1}, 5: {1}} == seen[4]
    whole = rows(emit.all_members(spark.createDataFrame([(1, 1), (1, 2), (1, 4), (5, 3), (5, 4), (5, 5)], "key long, member long")).distinct())
    assert whole[4] == {1, 2, 3, 4, 5}


def test_upper_core_without_repair_splits(spark):
    edges = shuffled_path(96, 1)
    g = graph(spark.createDataFrame(edges, "src long, dst long"))
    split = components.upper_core(g, repair="none").components.select("component").distinct().count()
    assert split > 1
    whole = components.upper_core(g)
    assert whole.components.select("component").distinct().count() == 1


def test_rows_of_a_hub_are_spread(spark):
    """A star of 6000 leaves over 64 partitions: no partition gets much more than its share, and the answer is exact."""
    from pyspark.sql import functions as F

    from componentry.operators import emit
    from componentry.plans.rounds import init_closed

    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        edges = [(0, i) for i in range(1, 6001)] + [(10_000 + i, 10_001 + i) for i in range(0, 4000, 2)]
        g = graph(spark.createDataFrame(edges, "src long, dst long"))
        run = components.min_owner_balanced(g)
        assert dict(map(tuple, run.components.collect())) == union_find(edges)
        seen = []
        real = emit.merge_split
        emit.merge_split = lambda *a: seen.append(real(*a)) or seen[-1]
        try:
            components.min_owner_balanced(g)
            assert dict(map(tuple, components.min_owner_balanced(g, tau=50).components.collect())) == union_find(edges)
        finally:
            emit.merge_split = real
        # ids of other kinds, over and under tau
        named = g.edges.selectExpr("cast(lpad(src, 6, '0') as binary) as src", "cast(lpad(dst, 6, '0') as binary) as dst")
        for tau in (50, 100_000):
            got = components.min_owner_balanced(components.Graph(named), tau=tau).components.selectExpr("cast(cast(id as string) as int) i", "cast(cast(component as string) as int) c")
            assert dict(map(tuple, got.collect())) == union_find(edges)
        assert len(seen) >= 2
        dealt = seen[0].groupBy(F.spark_partition_id()).count().agg(F.max("count"), F.sum("count")).first()
        assert dealt[0] < 0.1 * dealt[1]
        plain = emit.merge_union(init_closed(g), size=True)
        assert sorted(map(tuple, seen[0].select("key", "member", "owner").collect())) == sorted(map(tuple, plain.select("key", "member", "owner").collect()))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


def test_recursive_query_tells_of_a_small_depth(spark):
    edges = graph(spark.createDataFrame([(i, i + 1) for i in range(6)], "src long, dst long")).edges
    assert baselines.recursive_cte_components(edges, 8).select("component").distinct().count() == 1
    with pytest.raises(NotConverged):
        baselines.recursive_cte_components(edges, 3)


def test_runs_side_by_side(spark):
    """Simultaneous runs over one graph keep caches of their own, free them, and find the same."""
    from componentry import workloads
    from componentry.operators import measures

    held = len(spark.sparkContext._jsc.getPersistentRDDs())
    edges = spark.createDataFrame(shuffled_path(12, 2) + [(50, 51)], "src long, dst long")
    for method in ("superstep", "neighbor_min", "min_owner"):
        got = measures.contention(lambda m=method: workloads.METHODS[m](graph(edges)), 4)
        assert got["median"] <= got["max"] and len(got["components"]) == 4
        for c in got["components"]:
            assert dict(map(tuple, c.collect())) == union_find(shuffled_path(12, 2) + [(50, 51)])
    assert len(spark.sparkContext._jsc.getPersistentRDDs()) == held


def test_all_members_of_a_large_group_of_copies(spark, tmp_path):
    """A group of n sends n^2 rows in its last round: 700^3 would be over any cap."""
    spark.range(700).selectExpr("id as doc_id", "'the same text' as text").write.parquet(f"{tmp_path}/documents.parquet")
    assert [tuple(r) for r in queries()["cc_all_members_doc_exact"](spark, str(tmp_path)).groupBy("component").count().collect()] == [(0, 700)]
    run = components.all_members(graph(spark.range(1, 700).selectExpr("0L as src", "id as dst")), once=True, member_cap=700 * 700 * 2)
    assert run.peak_messages <= 700 * 700 * 2 and run.components.select("component").distinct().count() == 1


def test_resident_rounds_of_a_small_graph_start_few_tasks(spark):
    """A small graph's resident rounds are a few tasks each, whatever the partitions; a larger one's are dealt, with the same result."""
    from componentry import workloads

    edges = shuffled_path(5, 2) + [(50, 51)]
    g = components.Graph(graph(spark.createDataFrame(edges, "src long, dst long")).edges.coalesce(1).localCheckpoint())
    before, rows = spark.conf.get("spark.sql.shuffle.partitions"), getattr(components, "RESIDENT_ROWS", 0)
    spark.conf.set("spark.sql.shuffle.partitions", "12")
    try:
        spark.sparkContext.setJobGroup("resident", "resident")
        run = baselines.superstep_min(g)
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        tracker = spark.sparkContext.statusTracker()
        stages = {s for j in tracker.getJobIdsForGroup("resident") for s in tracker.getJobInfo(j).stageIds}
        assert sum(i.numCompletedTasks for i in map(tracker.getStageInfo, stages) if i) < 12 * run.rounds_run
        components.RESIDENT_ROWS = 0
        assert components.resident_parts(g) == 12
        for f in (baselines.superstep_min, components.neighbor_min, components.upper_core):
            assert dict(map(tuple, f(g).components.collect())) == union_find(edges) == dict(map(tuple, run.components.collect()))
    finally:
        components.RESIDENT_ROWS = rows
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert workloads._outcomes([run.components, run.components.limit(0), run.components.where("id < 50")]) == [(7, 5, 2), (0, 0, 0), (5, 5, 1)]
