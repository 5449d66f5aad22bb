"""Single-linkage clustering with local stop tests.

Edges are ordered by (w, src, dst), so the closest pair is always one pair. A *core* is a node of the merge tree
of the whole graph: a single vertex, or two cores each of which is the other's nearest. The result, by any of
the methods here, is the cut of that tree: a merge counts if both halves count and neither is stopped.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.functions.graphs import Graph, lighter, normalize_wedges
from componentry.operators import emit
from componentry.operators.components import finished_components, min_owner_balanced
from componentry.operators.contract import DisjointSets, forest_edges
from componentry.operators.stops import Stop
from componentry.plans.rounds import Loop, NotConverged, RunResult, init_closed
from componentry.plans.storage import cut, release, small_side

_INF = math.inf


def cluster_distance(assign: DataFrame, wedges: DataFrame) -> DataFrame:
    """(c1, c2, w, src, dst): the lightest edge between each two clusters that an edge joins, c1 < c2."""
    a = assign.select(F.col("id").alias("src"), F.col("component").alias("ca"))
    b = assign.select(F.col("id").alias("dst"), F.col("component").alias("cb"))
    rows = wedges.join(a, "src").join(b, "dst").where("ca <> cb")
    return rows.groupBy(F.least("ca", "cb").alias("c1"), F.greatest("ca", "cb").alias("c2")).agg(F.min(F.struct("w", "src", "dst")).alias("x")).select("c1", "c2", "x.w", "x.src", "x.dst")


# -- one worker's part


@dataclass(slots=True)
class Node:
    """A core: how many vertices it has, whether it counts, its halves (or its one vertex), and the least weight that leads out of it."""

    size: int
    vertex: object = None
    counts: bool = True
    halves: tuple = ()
    nearest: float = _INF

    @property
    def members(self) -> list:
        todo, out = [self], []
        while todo:
            x = todo.pop()
            if x.halves:
                todo.extend(x.halves)
            else:
                out.append(x.vertex)
        return out


def merge_tree(members: set, edges: list[tuple], stop: Stop) -> list[Node]:
    """Largest cores inside ``members``, from all edges (w, src, dst) that touch them, in one pass over the edges by weight.

    An edge that comes up between two clusters is the nearest of each, unless one of them has met its nearest before and
    could not merge: that one grows no further, nor does a cluster whose nearest it is. Edges that lead
    out take part as what they are: a core whose nearest vertex lies outside grows no further.
    """
    ids = list(members)
    place = {m: i for i, m in enumerate(ids)}
    ends = ((w, place.get(a, -1), place.get(b, -1)) for w, a, b in sorted(set(edges)))
    return _grow(ids, ((w, max(i, k), min(i, k)) for w, i, k in ends if i >= 0 or k >= 0), stop)


def _grow(ids: Iterable, edges: Iterable[tuple[float, int, int]], stop: Stop) -> list[Node]:
    """merge_tree over places in ``ids``: edges (w, place, place) come in order, and one that leads out has -1 as its second place."""
    node = [Node(1, m) for m in ids]
    up = list(range(len(node)))
    ended = [False] * len(node)

    def end(x: int, w: float) -> None:
        if not ended[x]:
            ended[x], node[x].nearest = True, w

    for w, i, k in edges:
        while up[i] != i:
            up[i] = i = up[up[i]]
        if k < 0:
            end(i, w)
            continue
        while up[k] != k:
            up[k] = k = up[up[k]]
        if i == k:
            continue
        if ended[i] or ended[k]:
            end(i, w)
            end(k, w)
            continue
        own, mate = node[i], node[k]
        own.nearest = mate.nearest = w
        if own.size < mate.size:
            i, k = k, i
        up[k] = i
        node[i] = Node(own.size + mate.size, None, own.counts and mate.counts and not stop(own.size, w) and not stop(mate.size, w), (own, mate))
    return [node[i] for i in range(len(node)) if up[i] == i]


def cut_tree(n: Node) -> list[Node]:
    """Largest nodes below ``n`` that count."""
    todo, out = [n], []
    while todo:
        x = todo.pop()
        if x.counts:
            out.append(x)
        else:
            todo.extend(x.halves)
    return out


def is_core(members: set, edges: list[tuple]) -> bool:
    """Whether ``members`` is one core, judged from all edges that touch them."""
    found = merge_tree(members, edges, _never)
    return len(found) == 1 and found[0].size == len(members)


class _Never(Stop):
    def __call__(self, size: int, nearest: float) -> bool:
        return False


_never = _Never()


def spanning_tree(edges: list[tuple]) -> list[tuple]:
    """Minimum spanning forest of (w, src, dst)."""
    sets = DisjointSets()
    return [e for e in sorted(edges) if sets.join(e[1], e[2])]


def split(members: set, edges: list[tuple]) -> tuple[set, set]:
    """Two halves of a connected cluster: its spanning tree without the heaviest edge."""
    inner = [e for e in edges if e[1] in members and e[2] in members]
    tree = spanning_tree(inner)
    sets = DisjointSets()
    for _, a, b in tree[:-1]:
        sets.join(a, b)
    root = sets.find(tree[-1][1])
    left = {m for m in members if sets.find(m) == root}
    return left, members - left


# -- sequential


def slc_sequential(wedges: list[tuple], stop: Stop, vertices: set | None = None, scope: str = "cluster", row_cap: int = 1_000_000) -> dict:
    """id -> least id of its cluster, by merging the closest pair of clusters until nothing is left to merge; ``wedges`` are (w, src, dst).

    ``scope="cluster"``: a merge counts if both sides count and neither is stopped at its distance; a pair whose merge does not
    count goes on as one cluster that has given up growing, and each id stays in the last cluster of its own that counted.
    ``scope="run"``: the first pair of which either side is stopped ends the whole run.
    """
    if len(wedges) > row_cap:
        raise ValueError(f"over {row_cap} edges")
    if scope not in ("cluster", "run"):
        raise ValueError(scope)
    ids = {x for e in wedges for x in e[1:]} | (vertices or set())
    numbers = {i: n for n, i in enumerate(ids)}
    held = {n: {i} for i, n in numbers.items()}  # the live clusters by number
    counts = dict.fromkeys(held, True)
    far: dict[int, dict[int, tuple]] = {n: {} for n in held}  # the least edge to each cluster beside
    for e in wedges:
        a, b = numbers[e[1]], numbers[e[2]]
        if a != b and (b not in far[a] or e < far[a][b]):
            far[a][b] = far[b][a] = e
    pairs = [(e, a, b) for a, own in far.items() for b, e in own.items() if a < b]
    heapq.heapify(pairs)
    out: dict = {i: i for i in ids}
    new = len(ids)
    while pairs:
        e, a, b = heapq.heappop(pairs)
        if a not in held or b not in held or far[a].get(b) != e:
            continue  # one of them has been merged since
        stopped = stop(len(held[a]), e[0]) or stop(len(held[b]), e[0])
        if stopped and scope == "run":
            break
        whole = held.pop(a) | held.pop(b)
        counts[new] = counts.pop(a) & counts.pop(b) & (not stopped)
        held[new], far[new] = whole, {}
        if counts[new]:
            out.update(dict.fromkeys(whole, min(whole)))
        for side in (far.pop(a), far.pop(b)):
            for c, x in side.items():
                if c in held and c != new and (c not in far[new] or x < far[new][c]):
                    far[new][c] = x
        for c, x in far[new].items():
            far[c].pop(a, None)
            far[c].pop(b, None)
            far[c][new] = x
            heapq.heappush(pairs, (x, c, new))
        new += 1
    return out


# -- distributed rounds with the stop test


_CORES = T.StructType([T.StructField("key", T.LongType()), T.StructField("core", T.LongType()), T.StructField("member", T.LongType()), T.StructField("size", T.LongType()), T.StructField("stopped", T.BooleanType())])
_PARTS = T.StructType([T.StructField("cluster", T.LongType()), T.StructField("member", T.LongType()), T.StructField("size", T.LongType())])


def attach_edges(clusters: DataFrame, wedges: DataFrame) -> DataFrame:
    """(key, member, w, src, dst): each member of a cluster with the edges that touch it, one row without where none does."""
    ends = wedges.select("w", "src", "dst", F.explode(F.array("src", "dst")).alias("member"))
    return clusters.select("key", "member").join(ends, "member", "left")


#: rows of whole clusters that a worker takes at a time; a larger cluster is taken alone
CLUSTER_ROWS = 200_000


def _by_cluster(attached: DataFrame, schema: T.StructType, solve: Callable[[pa.Table], pa.Table]) -> DataFrame:
    """``solve`` over tables of whole clusters: rows are dealt and ordered by key, and a table ends where a key does."""
    most = CLUSTER_ROWS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            rows += batch.num_rows
            last = batch["key"][-1].as_py()
            if rows >= most and held[0]["key"][0].as_py() != last:
                table = pa.Table.from_batches(held)
                at = int(np.searchsorted(table["key"].to_numpy(), last))
                yield from solve(table.slice(0, at)).to_batches()
                held, rows = table.slice(at).to_batches(), table.num_rows - at
        if rows:
            yield from solve(pa.Table.from_batches(held)).to_batches()

    return attached.repartition("key").sortWithinPartitions("key").mapInArrow(run, schema)


def _placed(table: pa.Table) -> tuple[np.ndarray, np.ndarray, Iterator[tuple[float, int, int]]]:
    """(key, member) in order without repeats, and the edges between their places as _grow takes them.

    An edge inside a cluster comes with either end as its member, one that leads out with one of them.
    """
    key, member = (table[c].to_numpy() for c in ("key", "member"))
    order = np.lexsort((member, key))
    first = np.ones(len(order), bool)
    first[1:] = (np.diff(key[order]) != 0) | (np.diff(member[order]) != 0)
    place = np.empty(len(order), np.int64)
    place[order] = np.cumsum(first) - 1
    known = table["w"].is_valid().to_numpy()
    rows = table.filter(pa.array(known))
    w, src, dst = (rows[c].to_numpy() for c in ("w", "src", "dst"))
    own, at = key[known], place[known]
    by = np.lexsort((at, own, dst, src, w))
    w, src, dst, own, at = w[by], src[by], dst[by], own[by], at[by]
    new = np.ones(len(by), bool)
    new[1:] = (np.diff(own) != 0) | (np.diff(src) != 0) | (np.diff(dst) != 0) | (w[1:] != w[:-1])
    begin = np.flatnonzero(new)
    low, high = at[begin], at[np.append(begin[1:], len(by)) - 1] if len(begin) else at
    return key[order][first], member[order][first], zip(w[begin].tolist(), high.tolist(), np.where(low == high, -1, low).tolist(), strict=True)


def minimal_cores(attached: DataFrame, stop: Stop) -> DataFrame:
    """(key, core, member, size, stopped) of the largest cores in each cluster, many clusters a worker call."""

    def solve(table: pa.Table) -> pa.Table:
        keys, ids, edges = _placed(table)
        found = _grow(range(len(ids)), edges, stop)
        held = [n.members for n in found]
        size = np.array([n.size for n in found], np.int64)
        flat = np.array([i for own in held for i in own], np.int64)
        core = np.repeat(ids[[min(own) for own in held]], size)
        done = np.repeat([(not n.counts) or bool(stop(n.size, n.nearest)) for n in found], size)
        return pa.table({"key": keys[flat], "core": core, "member": ids[flat], "size": np.repeat(size, size), "stopped": done})

    return _by_cluster(attached, _CORES, solve)


def stop_reached(cores: DataFrame) -> bool:
    """Whether for every member the largest core that any cluster has of it is stopped."""
    best = cores.groupBy("member").agg(F.max(F.struct("size", "stopped")).alias("x"))
    return bool(best.agg(F.coalesce(F.bool_and("x.stopped"), F.lit(True))).first()[0])


def split_wrong_merges(attached: DataFrame, stop: Stop) -> DataFrame:
    """(cluster, member, size): cores cut down to the nodes that count."""

    def solve(table: pa.Table) -> pa.Table:
        _, ids, edges = _placed(table)
        held = [part.members for n in _grow(range(len(ids)), edges, stop) for part in cut_tree(n)]
        size = np.array([len(own) for own in held], np.int64)
        flat = np.array([i for own in held for i in own], np.int64)
        return pa.table({"cluster": np.repeat(ids[[min(own) for own in held]], size), "member": ids[flat], "size": np.repeat(size, size)})

    return _by_cluster(attached, _PARTS, solve)


def slc_rounds(wedges: DataFrame, stop: Stop, *, hashing: str = "min_owner", vertices: DataFrame | None = None, max_rounds: int = 64, retire: bool = False) -> RunResult:
    """Component rounds, a stop test after each, and a last split of merges that went too far.

    ``retire`` (min_owner hashing): components found whole leave the later rounds and the later tests.

    A worker holds each cluster whole in the test and the split; use slc_dendrogram_cut where they do not fit.
    """
    wedges = cut(normalize_wedges(wedges), "wedges")
    g = Graph(wedges.select("src", "dst"), vertices)
    loop = Loop(f"slc_{hashing}", max_rounds=max_rounds)
    if hashing == "min_owner":
        send, merge = emit.min_owner, emit.merge_union
        held = lambda s: s.where("key = owner")  # noqa: E731  all other keys hold parts of what owners hold
        loop.start(emit.merge_union(init_closed(g)))
    elif hashing == "all_members":
        send, merge = emit.all_members_once, lambda m: m.repartition("key").dropDuplicates(["key", "member"])
        held = emit.unlike  # of clusters that many keys hold alike one is enough
        loop.start(init_closed(g).distinct())
    else:
        raise ValueError(hashing)
    done: list[DataFrame] = []
    while True:
        changed = loop.step(send, merge)
        if not changed or not loop.stats[-1]["state_rows"]:
            break
        attached = attach_edges(_covering(loop.state, held), wedges)
        cores = cut(minimal_cores(attached, stop), "cores")
        if stop_reached(cores):
            break
        if retire and hashing == "min_owner":
            before, whole = loop.state, cut(finished_components(loop.state), "retired")
            if not whole.isEmpty():
                done.append(whole)
                loop.state = cut(before.join(whole.select(F.col("id").alias("key")), "key", "left_anti"), "slc")
                release(before)
        release(cores)
    clusters = _covering(loop.state, held)
    for whole in done:
        clusters = clusters.unionByName(whole.select(F.col("component").alias("key"), F.col("id").alias("member")))
    parts = split_wrong_merges(attach_edges(clusters, wedges), stop)
    best = parts.groupBy("member").agg(F.max(F.struct("size", -F.col("cluster"))).alias("x"))
    out = cut(best.select(F.col("member").alias("id"), (-F.col("x.col2")).alias("component")), "slc")
    return RunResult(out, loop.stats, {"stop": repr(stop), "hashing": hashing, "retired": len(done)})


def _covering(state: DataFrame, held) -> DataFrame:
    """Clusters that matter, and each vertex alone where none of them has it."""
    own = held(state).select("key", "member")
    rest = state.select(F.col("key").alias("member")).distinct().join(own, "member", "left_anti").select(F.col("member").alias("key"), "member")
    return own.unionByName(rest)


# -- by joins alone


def slc_dendrogram_cut(wedges: DataFrame, stop: Stop, *, vertices: DataFrame | None = None, max_rounds: int = 10_000, precontract: bool = True) -> RunResult:
    """The tree's cut by rounds of joins: each round merges the clusters that are each other's nearest.

    ``precontract``: blocks of edges become forests, and connected components of up to CLUSTER_ROWS of their edges are merged
    many to a worker call; the rounds have the larger ones. Beyond that no cluster is ever held whole, only its size. A cluster that
    meets a stopped one, or is stopped itself when its mate is found, is frozen; a cluster whose nearest is frozen freezes too.
    """
    wedges = normalize_wedges(wedges)
    stats, r, settled = [], 0, None
    ids = Graph(wedges.select("src", "dst"), vertices).ids
    if precontract:
        wedges = cut(forest_edges(wedges), "forest")
        ids = Graph(wedges.select("src", "dst"), vertices).ids
        settled, wedges = _settled_blocks(wedges, stop)
        ids = ids.join(settled.select("id"), "id", "left_anti")
        n = settled.count()
        stats.append({"run": "slc_dendrogram_cut", "round": 0, "phase": "blocks", "messages_emitted": n, "state_rows": n, "changed": n > 0, "seconds": 0.0})
    assign = cut(ids.select("id", F.col("id").alias("component")), "assign")
    clusters = cut(ids.select(F.col("id").alias("c"), F.lit(1).cast("long").alias("size"), F.lit(False).alias("frozen")), "clusters")
    edges = cut(wedges.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.struct("w", "src", "dst").alias("e")), "cedges")
    while not edges.isEmpty():
        r += 1
        if r > max_rounds:
            raise NotConverged(f"slc: no end after {max_rounds} rounds", stats)
        both = edges.select("a", "b", "e").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "e"))
        near = both.groupBy("a").agg(F.min(F.struct("e", "b")).alias("x")).select(F.col("a").alias("c"), F.col("x.b").alias("to"), F.col("x.e").alias("e"))
        facts = clusters.where("not frozen").join(near, "c")
        mate = clusters.select(F.col("c").alias("to"), F.col("size").alias("to_size"), F.col("frozen").alias("to_frozen"))
        back = near.select(F.col("c").alias("to"), F.col("to").alias("back"))
        seen = facts.join(mate, "to").join(back, "to", "left")
        mutual = ~F.col("to_frozen") & (F.col("back") == F.col("c"))
        stopped = stop.column(F.col("size"), F.col("e.w")) | stop.column(F.col("to_size"), F.col("e.w"))
        verdict = cut(seen.select("c", "to", "size", "to_size", F.when(F.col("to_frozen"), "freeze").when(mutual & stopped, "freeze").when(mutual, "merge").otherwise("wait").alias("v")), "verdict")
        moves = verdict.where("v = 'merge' and c > to").select(F.col("c").alias("old"), F.col("to").alias("new"))
        cold = verdict.where("v = 'freeze'").select("c", F.lit(True).alias("cold"))
        named = clusters.join(moves, F.col("c") == F.col("old"), "left").join(cold, "c", "left")
        new_clusters = cut(named.groupBy(F.coalesce("new", "c").alias("c")).agg(F.sum("size").alias("size"), F.max(F.col("frozen") | F.coalesce("cold", F.lit(False))).alias("frozen")), "clusters")
        new_assign = cut(assign.join(moves, F.col("component") == F.col("old"), "left").select("id", F.coalesce("new", "component").alias("component")), "assign")
        live = new_clusters.select("c", "frozen")
        renamed = edges.join(moves.withColumnRenamed("new", "na"), F.col("a") == F.col("old"), "left").drop("old").join(moves.withColumnRenamed("new", "nb"), F.col("b") == F.col("old"), "left")
        renamed = renamed.select(F.coalesce("na", "a").alias("a"), F.coalesce("nb", "b").alias("b"), "e").where("a <> b")
        fa, fb = (live.select(F.col("c").alias(x), F.col("frozen").alias("f" + x)) for x in "ab")
        new_edges = cut(renamed.join(fa, "a").join(fb, "b").where("not (fa and fb)").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.min("e").alias("e")), "cedges")
        n = verdict.agg(F.count_if(F.col("v") != "wait").alias("n"), F.count(F.lit(1)).alias("m")).first()
        stats.append({"run": "slc_dendrogram_cut", "round": r, "phase": "round", "messages_emitted": n["m"], "state_rows": n["m"], "changed": n["n"] > 0, "seconds": 0.0})
        release(clusters, assign, edges, verdict)
        clusters, assign, edges = new_clusters, new_assign, new_edges
        if not n["n"]:
            break
    return RunResult(assign if settled is None else assign.unionByName(settled), stats, {"stop": repr(stop)})


def _settled_blocks(wedges: DataFrame, stop: Stop) -> tuple[DataFrame, DataFrame]:
    """(id, component) of the cut inside the connected components of up to CLUSTER_ROWS edges, and the edges of the others."""
    pieces = cut(min_owner_balanced(Graph(wedges.select("src", "dst")), precontract=True, stats=False).components.select("id", F.col("component").alias("key")), "pieces")
    sizes = wedges.join(pieces.withColumnRenamed("id", "src"), "src").groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    large = small_side(cut(sizes.where(F.col("n") > CLUSTER_ROWS).select("key"), "large"), 8)
    small = pieces.join(large, "key", "left_anti").withColumnRenamed("id", "member")
    parts = split_wrong_merges(attach_edges(small, wedges), stop)
    settled = cut(parts.select(F.col("member").alias("id"), F.col("cluster").alias("component")), "settled")
    rest = cut(wedges.join(pieces.join(large, "key", "left_semi").select(F.col("id").alias("src")), "src", "left_semi"), "rest")
    release(pieces)
    return settled, rest


def slc_threshold(wedges: DataFrame, theta: float, vertices: DataFrame | None = None, **opts) -> RunResult:
    """The cut at a distance: components over the edges of weight at most ``theta``."""
    wedges = normalize_wedges(wedges)
    ids = Graph(wedges.select("src", "dst"), vertices).ids
    return min_owner_balanced(Graph(lighter(wedges, theta).select("src", "dst"), ids), **opts)
