"""Connected components of undirected graphs: the round methods and their variants.

All return RunResult with ``components(id, component)``, component = least id (in the natural order).
``order="random"`` runs over a seeded random relabelling of the ids and translates the result back.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from componentry.functions.graphs import Graph, adjacency, graph, mix64, normalize_edges, touched
from componentry.operators import emit
from componentry.operators.contract import star_edges
from componentry.plans.rounds import Loop, NotConverged, RunResult, export_by_label, export_owner_clusters, init_closed, init_self, original_order
from componentry.plans.storage import cut, release, small_side

TAU = 100_000
HUB_ROWS = 1024
#: rows of an adjacency that one task may hold: rounds of smaller graphs would be a matter of starting tasks
RESIDENT_ROWS = 1_000_000


def _ordered(g: Graph, order: str, seed: int, run: Callable[[Graph], RunResult]) -> RunResult:
    if order == "natural":
        return run(g)
    if order != "random":
        raise ValueError(order)
    mix = lambda c: mix64(F.col(c), seed)
    ids = g.ids
    mixed = Graph(normalize_edges(g.edges.select(mix("src").alias("src"), mix("dst").alias("dst"))), None if g.vertices is None else ids.select(mix("id").alias("id")))
    out = run(mixed)
    out.components = original_order(out.components, ids.select("id", mix("id").alias("rank")))
    out.meta["order"] = f"random({seed})"
    return out


def _loop(name: str, opts: dict) -> Loop:
    return Loop(name, **{k: v for k, v in opts.items() if k in ("max_rounds", "detect", "row_cap", "stats")})


def resident_parts(g: Graph) -> int:
    """Partitions for the adjacency of ``g``: one for a small graph, else as many as any exchange has."""
    return 1 if 2 * g.edges.count() <= RESIDENT_ROWS else int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def dealt(df: DataFrame, parts: int) -> DataFrame:
    """``df`` in ``parts`` partitions by id, or in one."""
    return df.coalesce(1) if parts == 1 else df.repartition(parts, "id")


@contextmanager
def resident(g: Graph, parts: int | None = None) -> Iterator[DataFrame]:
    """Adjacency dealt by id once and kept so, on disk where memory lacks: rounds move labels, never edges.

    The cache knows frames by their plans; a mark that is true of every row makes this one the run's own, so that
    runs side by side over one graph do not drop each other's.
    """
    nbrs = adjacency(g.edges).where(F.lit(uuid.uuid4().hex) != "")
    nbrs = dealt(nbrs, parts or resident_parts(g)).persist()
    try:
        yield nbrs
    finally:
        nbrs.unpersist()


def neighbor_min(g: Graph, *, order: str = "natural", seed: int = 42, frontier: bool = False, **opts) -> RunResult:
    """The least id known travels one hop a round. ``frontier``: only keys whose label changed send it on."""

    def run(g: Graph) -> RunResult:
        loop = _loop("neighbor_min", {"max_rounds": 10_000} | opts)
        loop.start(init_self(g.ids).withColumn("fresh", F.lit(True)))

        def merge(messages: DataFrame) -> DataFrame:
            seen = messages.groupBy("key").agg(F.min("member").alias("member"), F.min(F.when(F.col("own"), F.col("member"))).alias("was"))
            return seen.select("key", "member", (F.col("member") < F.col("was")).alias("fresh"))

        with resident(g) as nbrs:

            def send(state: DataFrame) -> DataFrame:
                live = state.where("fresh") if frontier else state
                own = state.select("key", "member", F.lit(True).alias("own"))
                return own.unionByName(emit.neighbor_min(live, nbrs).withColumn("own", F.lit(False)))

            loop.until_stable(send, merge)
        return RunResult(loop.state.select(F.col("key").alias("id"), F.col("member").alias("component")), loop.stats)

    return _ordered(g, order, seed, run)


def all_members(g: Graph, *, order: str = "natural", seed: int = 42, member_cap: int | None = None, once: bool = False, **opts) -> RunResult:
    """Every member gets the whole cluster each round: fewest rounds, exchange quadratic in the largest component.

    ``once``: a cluster that many keys hold alike is sent by one of them. The states are the same; a component of n ids,
    once each holds it whole, sends n^2 rows and not n^3. ``member_cap`` bounds the messages of a round, counted from the cluster sizes before they are sent;
    past it NotConverged is raised (a DNF).
    """

    def run(g: Graph) -> RunResult:
        loop = _loop("all_members", opts)
        loop.start(init_closed(g).distinct())

        def due(state: DataFrame) -> None:
            if member_cap is not None:
                sent = (emit.unlike(state) if once else state).groupBy("key").count().agg(F.sum(F.col("count").cast("decimal(38,0)") * F.col("count"))).first()[0] or 0
                if sent > member_cap:
                    raise NotConverged(f"all_members: {sent} messages are due; the cap is {member_cap}", loop.stats)

        while True:
            due(loop.state)
            if not loop.step(emit.all_members_once if once else emit.all_members, lambda m: m.repartition("key").dropDuplicates(["key", "member"])):
                break
        return RunResult(export_by_label(loop.state), loop.stats)

    return _ordered(g, order, seed, run)


def _contracted(g: Graph, precontract: bool) -> Graph:
    return Graph(star_edges(g.edges), g.vertices) if precontract else g


def finished_components(state: DataFrame) -> DataFrame:
    """(id, component) of the components that are whole stars in a min_owner state: nothing outside touches them."""
    sizes = state.groupBy("key", "owner").agg(F.count(F.lit(1)).alias("n")).where("key <> owner")
    owners = state.where("key = owner").select(F.col("key").alias("component"), "member")
    answers = sizes.where("n = 1").select(F.col("key").alias("member"), F.col("owner").alias("to"))
    open_members = owners.where("member <> component").join(answers, "member", "left").where("to is null or to <> component").select("component")
    loose = state.join(sizes.where("n > 1").select("key"), "key", "left_semi").select("member").distinct()
    unsettled = open_members.unionByName(owners.join(loose, "member", "left_semi").select("component")).distinct()
    return owners.join(unsettled, "component", "left_anti").select(F.col("member").alias("id"), "component")


def min_owner(g: Graph, *, order: str = "natural", seed: int = 42, precontract: bool = False, retire: bool = False, **opts) -> RunResult:
    """A cluster goes whole to its least member, the others hear only of that member. One exchange a round.

    ``precontract``: blocks of edges first become stars around their least ids. ``retire``: finished
    components (a star that a round left as it was) leave the later rounds. ``after`` is shown the loop at the start and
    after each productive round, and ends the run where it says True.
    """

    def run(g: Graph) -> RunResult:
        g = _contracted(g, precontract)
        loop = _loop("min_owner", opts)
        loop.start(emit.merge_union(init_closed(g)))
        if not retire:
            after = opts.get("after")
            if after is not None:
                after(loop)
            loop.until_stable(emit.min_owner, emit.merge_union, after=after)
            return RunResult(export_owner_clusters(loop.state), loop.stats)
        done: list[DataFrame] = []

        def settle(loop: Loop) -> bool:
            """Move components out whose owner's members all hold the owner and themselves at most."""
            state = loop.state
            finished = cut(finished_components(state), "retired")
            if not finished.isEmpty():
                done.append(finished)
                loop.state = cut(state.join(finished.select(F.col("id").alias("key")), "key", "left_anti"), "min_owner")
                release(state)
            return loop.state.isEmpty()

        loop.until_stable(emit.min_owner, emit.merge_union, after=settle)
        out = export_owner_clusters(loop.state)
        for part in done:
            out = out.unionByName(part)
        return RunResult(out, loop.stats, {"retired_rounds": len(done)})

    return _ordered(g, order, seed, run)


def _splitting(loop: Loop, tau: int) -> Callable[[DataFrame], DataFrame]:
    """A merge step that spreads the rows of hubs: keys with over four times a partition's even share of the messages.

    Hubs are looked for where one is to be expected: at the start, and once the largest cluster comes near that share.
    Fewer than a quarter as many keys as partitions can be hubs, so their list is small. Sizes are counted exactly
    where they may be over ``tau``; below, a hub's messages stand for them.
    """

    def merge(messages: DataFrame) -> DataFrame:
        spark = messages.sparkSession
        parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
        rows = loop.stats[-1]["state_rows"] if loop.stats else messages.count()
        even = max(HUB_ROWS, 4 * 2 * rows // parts)
        if rows > even and (not loop.stats or 4 * loop.largest > even):
            counts = messages.groupBy("key").agg(F.min("member").alias("head"), F.count(F.lit(1)).alias("all"), F.max(F.col("member") == F.col("key")).alias("self")).where(F.col("all") > even)
            found = counts.collect()  # fewer than a quarter of the partitions
            if any(r["all"] > tau for r in found):
                few = F.broadcast(spark.createDataFrame(found, counts.schema))
                exact = messages.join(few.select("key"), "key").distinct().groupBy("key").agg(F.count(F.lit(1)).alias("n"))
                found = few.join(exact, "key").select("key", "head", F.col("n").alias("all"), "self").collect()
            if found:
                return emit.merge_split(messages, spark.createDataFrame(found, counts.schema), min(parts, 64))
        return emit.merge_union(messages, size=True)

    return merge


def min_owner_balanced(g: Graph, *, tau: int | None = TAU, order: str = "natural", seed: int = 42, precontract: bool = False, **opts) -> RunResult:
    """min_owner in which clusters over ``tau`` keep their upper half, then the plain method over the clusters found.

    ``tau`` bounds what a cluster sends on, not what a key holds: a hub holds its neighbours from the start. The rows of
    such keys are dealt over many tasks (see ``_splitting``), so no task grows with the largest component.
    """

    def run(g: Graph) -> RunResult:
        g = _contracted(g, precontract)
        first = _loop("min_owner_balanced", opts)
        most = tau if tau is not None else (1 << 62)
        merge = _splitting(first, most)
        first.start(merge(init_closed(g)))
        first.until_stable(lambda s: emit.min_owner_balanced(s, most), merge, "stage 1")
        if first.state.where(F.col("size") > most).isEmpty():
            # no key kept anything back: this is a fixed point of the plain method
            return RunResult(export_owner_clusters(first.state), first.stats, {"stage1_rounds": first.rounds, "stage2_rounds": 0})
        # each id names the cluster it answers to: the least member it holds
        named = cut(export_by_label(first.state), "named")
        links = first.state.select("key", "member").where("key <> member")
        a, b = named.select(F.col("id").alias("key"), F.col("component").alias("src")), named.select(F.col("id").alias("member"), F.col("component").alias("dst"))
        quotient = cut(normalize_edges(links.join(a, "key").join(b, "member").select("src", "dst")), "quotient")
        release(first.state)
        heads = named.select(F.col("component").alias("id")).distinct()
        second = _loop("min_owner_balanced", opts)
        merge = _splitting(second, most)
        second.start(merge(init_closed(Graph(quotient, heads))), "stage 2")
        second.until_stable(emit.min_owner, merge, "stage 2")
        book = export_owner_clusters(second.state).select(F.col("id").alias("head"), "component")
        out = named.withColumnRenamed("component", "head").join(small_side(book), "head").select("id", "component")
        stats = first.stats + second.stats
        return RunResult(out, stats, {"stage1_rounds": first.rounds, "stage2_rounds": second.rounds})

    return _ordered(g, order, seed, run)


def upper_core(g: Graph, *, order: str = "natural", seed: int = 42, repair: str = "root_forward", keep_self: bool = False, **opts) -> RunResult:
    """Triples of rounds: two of neighbor_min that grow the clusters, one that sends the members from the key up to the least.

    ``repair``: ``root_forward`` (in the second round the least known is also told to the least known
    before), ``wide`` (told to the whole cluster) or ``none``, the rule without repair, which can stop
    with a component in parts. ``keep_self``: a key never gives up itself.
    """

    def run(g: Graph) -> RunResult:
        loop = _loop("upper_core", {"max_rounds": 300} | opts)
        loop.start(emit.with_owner(init_self(g.ids)))

        def grow(**told: bool) -> None:
            state = loop.state
            loop.step(lambda s: emit.tell(s, nbrs, **told), lambda m: emit.merge_keep_plus_min(state, m), "grow", compare=False)

        def last(state: DataFrame) -> DataFrame:
            sent = emit.upper_core(state)
            return sent.unionByName(state.select("key", F.col("key").alias("member")).distinct()) if keep_self else sent

        with resident(g) as nbrs:
            while True:
                grow(wide=repair == "wide")
                grow(wide=repair == "wide", root_forward=repair == "root_forward")
                if not loop.step(last, emit.merge_union, "core"):
                    break
        return RunResult(loop.state.where("member = owner").select(F.col("key").alias("id"), F.col("owner").alias("component")), loop.stats, {"repair": repair})

    return _ordered(g, order, seed, run)


def hybrid_mode_switch(g: Graph, *, tau: int = TAU, **opts) -> RunResult:
    """upper_core whose large clusters fall back to labels: keys over ``tau`` members, and their members, keep the least id only."""
    loop = _loop("hybrid_mode_switch", {"max_rounds": 10_000} | opts)
    loop.start(emit.with_owner(init_self(g.ids), size=True))
    with resident(g) as nbrs:

        def send(state: DataFrame) -> DataFrame:
            least = state.select("key", F.col("owner").alias("member")).distinct()
            flood = emit.neighbor_min(state.select("key", "member"), nbrs)
            held = state.where(f"size <= {tau} and member >= key")
            return least.unionByName(flood).unionByName(emit.pairs(held, ("owner", "member"), ("member", "owner")))

        loop.until_stable(send, lambda m: emit.merge_union(m, size=True))
    # labels settle by flooding; whatever clusters hold beyond that is dropped at the end
    return RunResult(export_by_label(loop.state), loop.stats)


def st_connected(g: Graph, s: int, t: int, **opts) -> bool:
    """Whether an undirected path joins ``s`` and ``t``: rounds of min_owner that stop when both answer to one owner."""
    loop = _loop("st_connected", opts)
    loop.start(emit.merge_union(init_closed(g)))
    met: list[bool] = []

    def together(loop: Loop) -> bool:
        rows = loop.state.where(F.col("key").isin(s, t)).select("key", "owner").distinct().limit(2).collect()
        if len(rows) == 2 and rows[0]["owner"] == rows[1]["owner"]:
            met.append(True)
        return bool(met)

    loop.until_stable(emit.min_owner, emit.merge_union, after=together)
    return bool(met) or together(loop) or (s == t and not g.ids.where(F.col("id") == s).isEmpty())


def choose_method(profile: dict, tau: int = TAU) -> tuple[str, list[str]]:
    """A method for a graph of this profile (keys of measures.profile, ``n`` an estimate): name and reasons."""
    n, v, e = profile.get("n", 0), profile.get("v", 0), profile.get("e", 0)
    if n and n <= 100 and n * v <= 100 * (v + e):
        return "all_members", [f"components have at most {n} ids: whole clusters cost little and end in the fewest rounds"]
    if n > tau or profile.get("max_degree", 0) > tau:
        return "min_owner_balanced", [f"a key would gather over {tau} rows"]
    return "min_owner", ["exchange stays linear in vertices and edges whatever the sizes"]


METHODS: dict[str, Callable[..., RunResult]] = {
    "neighbor_min": neighbor_min,
    "all_members": all_members,
    "min_owner": min_owner,
    "min_owner_balanced": min_owner_balanced,
    "upper_core": upper_core,
    "hybrid_mode_switch": hybrid_mode_switch,
}


def components(edges: DataFrame, vertices: DataFrame | None = None, method: str = "min_owner", **opts) -> RunResult:
    """Components of any (src, dst) frame by the method named."""
    from componentry.operators import baselines, secondary_sort

    every = METHODS | {"min_owner_sorted": secondary_sort.min_owner_sorted, "label_prop": baselines.label_prop_baseline, "superstep": baselines.superstep_min}
    return every[method](graph(edges, vertices), **opts)


__all__ = ["METHODS", "TAU", "all_members", "choose_method", "components", "hybrid_mode_switch", "min_owner", "min_owner_balanced", "neighbor_min", "st_connected", "touched", "upper_core"]
