"""Single linkage: all methods give the cut of the merge tree; stop tests."""

import inspect
import random

import pytest

from componentry import workloads
from componentry.operators import linkage
from componentry.operators.components import min_owner
from componentry.operators.stops import DistanceStop, LocalStop, NonLocalStopError, SizeStop, check_monotone, cluster_count_stop
from componentry.plans.rounds import NotConverged


def brute_cut(wedges, stop):
    """The tree by repeated search of the closest pair of clusters, cut from the top."""
    clusters = {frozenset([x]): True for e in wedges for x in e[1:]}
    kept = {c: [c] for c in clusters}
    while True:
        best = None
        for w, a, b in sorted(wedges):
            x = next(c for c in clusters if a in c)
            y = next(c for c in clusters if b in c)
            if x != y:
                best = (w, x, y)
                break
        if not best:
            break
        w, x, y = best
        ok = clusters.pop(x) and clusters.pop(y) if clusters[x] else (clusters.pop(x), clusters.pop(y))[0]
        ok = bool(ok) and not stop(len(x), w) and not stop(len(y), w)
        both = x | y
        clusters[both] = ok
        kept[both] = [both] if ok else kept[x] + kept[y]
    return {i: min(p) for c in clusters for p in kept[c] for i in p}


def random_weighted(seed):
    r = random.Random(seed)
    n = r.randrange(4, 14)
    out = {}
    for _ in range(r.randrange(n, 3 * n)):
        a, b = sorted(r.sample(range(n), 2))
        out[a, b] = r.choice([0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7])
    return [(w, a, b) for (a, b), w in out.items()]


@pytest.mark.parametrize("stop", [DistanceStop(0.35), SizeStop(3), SizeStop(2), LocalStop(lambda size, near: size >= 4 or near > 0.5)], ids=str)
def test_tree_cut_in_one_worker(stop):
    for seed in range(60):
        edges = random_weighted(seed)
        want = brute_cut(edges, stop)
        assert linkage.slc_sequential(edges, stop) == want, seed
        members = {x for e in edges for x in e[1:]}
        got = {}
        for n in linkage.merge_tree(members, edges, stop):
            for p in linkage.cut_tree(n):
                got.update(dict.fromkeys(p.members, min(p.members)))
        assert got == want, seed


def test_distributed_equals_the_tree_cut(spark):
    # many small graphs side by side in one run
    for stop in (DistanceStop(0.35), SizeStop(3)):
        edges, want = [], {}
        for seed in range(25):
            own = [(w, a + 100 * seed, b + 100 * seed) for w, a, b in random_weighted(seed)]
            edges += own
            want |= brute_cut(own, stop)
        df = spark.createDataFrame(edges, "w double, src long, dst long")
        for run in (
            lambda df, s: linkage.slc_rounds(df, s),
            lambda df, s: linkage.slc_rounds(df, s, hashing="all_members"),
            lambda df, s: linkage.slc_rounds(df, s, retire=True),
            lambda df, s: linkage.slc_dendrogram_cut(df, s),
        ):
            assert dict(map(tuple, run(df, stop).components.select("id", "component").collect())) == want


def test_threshold_is_the_distance_cut(spark):
    edges = random_weighted(3)
    df = spark.createDataFrame(edges, "w double, src long, dst long")
    got = dict(map(tuple, linkage.slc_threshold(df, 0.35).components.collect()))
    assert got == brute_cut(edges, DistanceStop(0.35))
    assert dict(map(tuple, linkage.slc_threshold(df, 9.0).components.collect())) == dict(map(tuple, min_owner(linkage.Graph(df.select("src", "dst"))).components.collect()))


def test_cores_and_split():
    edges = [(0.1, 1, 2), (0.2, 2, 3), (0.5, 3, 4), (0.1, 4, 5)]
    assert linkage.is_core({1, 2}, edges[:2])
    assert not linkage.is_core({2, 3}, edges)
    assert linkage.is_core({1, 2, 3}, edges[:3])
    assert linkage.split({1, 2, 3, 4, 5}, edges) in (({1, 2, 3}, {4, 5}), ({4, 5}, {1, 2, 3}))


def test_stops():
    for s in (DistanceStop(0.3), SizeStop(4)):
        check_monotone(s)
    with pytest.raises(ValueError):
        check_monotone(LocalStop(lambda size, near: size == 3))
    with pytest.raises(NonLocalStopError):
        cluster_count_stop(4)


def test_a_long_chain_in_one_worker():
    """Falling weights: the merge tree is one deep path, and every merge has live clusters beside it."""
    n = 20_000
    edges = [(1.0 + (n - i) / n, i, i + 1) for i in range(n)] + [(9.0, n, n + 1)]
    nodes = linkage.merge_tree(set(range(n + 1)), edges, SizeStop(10**9))
    assert [(x.size, x.nearest, x.counts) for x in nodes] == [(n + 1, 9.0, True)]
    assert sorted(linkage.cut_tree(nodes[0])[0].members) == list(range(n + 1))


def test_many_clusters_a_worker_call(spark, monkeypatch):
    """Clusters that overlap, cut by tables of any length: each is solved as if alone."""
    wedges = [(w, a + 20 * seed, b + 20 * seed) for seed in range(8) for w, a, b in random_weighted(seed)]
    ids = sorted({x for e in wedges for x in e[1:]})
    r = random.Random(4)
    held = {k: {k, *r.sample(ids, r.randrange(12))} for k in ids} | {-1: set(ids), -2: {10**9}}
    clusters = spark.createDataFrame([(k, m) for k, own in held.items() for m in own], "key long, member long").repartition(3)
    attached = linkage.attach_edges(clusters, spark.createDataFrame(wedges, "w double, src long, dst long"))
    for stop in (DistanceStop(0.35), SizeStop(3)):
        cores, parts = [], []
        for k, own in held.items():
            for n in linkage.merge_tree(own, [e for e in wedges if own & set(e[1:])], stop):
                cores += [(k, min(n.members), m, n.size, not n.counts or stop(n.size, n.nearest)) for m in n.members]
                parts += [(min(p.members), m, p.size) for p in linkage.cut_tree(n) for m in p.members]
        for rows in (1, 50, 200_000):
            monkeypatch.setattr(linkage, "CLUSTER_ROWS", rows)
            got = linkage.minimal_cores(attached, stop)
            assert "MapInArrow" in got._jdf.queryExecution().toString()  # no call for each cluster
            assert sorted(map(tuple, got.collect())) == sorted(cores)
            assert sorted(map(tuple, linkage.split_wrong_merges(attached, stop).collect())) == sorted(parts)


def test_no_run_of_the_clustering_table_ends_early(spark, monkeypatch):
    """A run that stops short has no row of its own: the table fails."""
    monkeypatch.setitem(workloads.GRAPHS, "chain", lambda spark, d: spark.range(40).selectExpr("id AS src", "id + 1 AS dst", "1.0D - id / 100 AS w"))
    row = workloads.clustering(spark, "", ("all_members",), ("chain",), (SizeStop(50),)).first()
    assert (row["v"], row["largest"], row["n_clusters"], row["dnf"], row["rounds_run"]) == (41, 41, 1, False, 7)
    whole = linkage.slc_rounds
    monkeypatch.setattr(linkage, "slc_rounds", lambda *a, **k: whole(*a, **k, max_rounds=2))
    with pytest.raises(NotConverged):
        workloads.clustering(spark, "", ("all_members",), ("chain",), (SizeStop(50),))
    assert "member_cap" not in inspect.signature(whole).parameters


def test_small_components_take_no_rounds_of_joins(spark, monkeypatch):
    """Falling weights: by joins a chain takes a round a vertex; larger components still go through them."""
    chains = [(1.0 - i / 100 + c / 10_000, 100 * c + i, 100 * c + i + 1) for c, n in enumerate((12, 5, 30)) for i in range(n)]
    df = spark.createDataFrame(chains, "w double, src long, dst long")
    ids = {x for e in chains for x in e[1:]} | {5000}
    lone = spark.createDataFrame([(i,) for i in sorted(ids)], "id long")
    for stop in (DistanceStop(0.8), SizeStop(4)):
        want = brute_cut(chains, stop) | {5000: 5000}
        run = linkage.slc_dendrogram_cut(df, stop, vertices=lone)
        assert run.rounds_run == 0
        assert dict(map(tuple, run.components.select("id", "component").collect())) == want
    monkeypatch.setattr(linkage, "CLUSTER_ROWS", 10)
    run = linkage.slc_dendrogram_cut(df.where("src < 200"), SizeStop(4), vertices=lone.where("id < 200 or id = 5000"))
    assert run.rounds_run > 0
    assert dict(map(tuple, run.components.select("id", "component").collect())) == {i: c for i, c in want.items() if i < 200 or i == 5000}
