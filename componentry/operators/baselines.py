"""What the round methods are compared with: label propagation, resident supersteps, and exact local answers."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from componentry.functions.graphs import Graph, adjacency
from componentry.operators.contract import DisjointSets, forest_edges
from componentry.plans.rounds import NotConverged, RunResult
from componentry.plans.storage import cut, release


def label_prop_baseline(g: Graph, *, order: str = "natural", seed: int = 42, blocks: bool = False, **opts) -> RunResult:
    """neighbor_min as a tuned package runs it: adjacency resident, labels combined before the exchange, changed labels only.

    ``blocks`` shrinks blocks of edges to forests first: less data, but longer paths and so more rounds.
    """
    from componentry.operators.components import neighbor_min

    out = neighbor_min(Graph(forest_edges(g.edges), g.ids) if blocks else g, order=order, seed=seed, frontier=True, **opts)
    return RunResult(out.components, [s | {"run": "label_prop"} for s in out.stats], {"blocks": blocks})


def superstep_min(g: Graph, *, supersteps: int = 4, max_rounds: int = 10_000, **opts) -> RunResult:
    """neighbor_min with resident state: adjacency and labels stay cached and dealt alike; files are written every ``supersteps`` rounds only.

    Every id tells every neighbour its label in each superstep, so a round's messages are the adjacency's rows. A round's plan
    has that of the round before twice, so few rounds may pass between files.
    """
    from componentry.operators.components import dealt, resident, resident_parts

    stats, rounds, parts = [], 0, resident_parts(g)
    settle = (lambda df: df.coalesce(1)) if parts == 1 else (lambda df: df)  # no exchange where all is in one partition
    with resident(g, parts) as nbrs:
        sent_rows = nbrs.count()
        held = dealt(g.ids.select("id", F.col("id").alias("label"), F.lit(uuid.uuid4().hex).alias("run")).drop("run"), parts).persist()
        labels = settle(held)
        try:
            while True:
                if rounds >= max_rounds:
                    raise NotConverged(f"superstep: no end after {rounds} rounds", stats)
                rounds += 1
                began = time.perf_counter()
                heard = settle(nbrs.join(labels.hint("shuffle_hash"), "id").groupBy(F.col("nbr").alias("id")).agg(F.min("label").alias("heard")))
                new = settle(labels.join(heard.hint("shuffle_hash"), "id", "left").select("id", F.least("label", "heard").alias("label"), (F.col("heard") < F.col("label")).alias("moved")))
                fresh = cut(new, "superstep") if rounds % supersteps == 0 else new.persist()
                moved = settle(fresh).agg(F.count_if("moved").alias("m"), F.count(F.lit(1)).alias("n")).first()
                _let_go(held)
                held, labels = fresh, settle(fresh.select("id", "label"))
                stats.append({"run": "superstep", "round": rounds, "phase": "round", "messages_emitted": sent_rows, "state_rows": moved["n"], "changed": moved["m"] > 0, "seconds": round(time.perf_counter() - began, 3)})
                if not moved["m"]:
                    break
            out = cut(labels, "superstep")
        finally:
            _let_go(held)
    return RunResult(out.select("id", F.col("label").alias("component")), stats)


def _let_go(held: DataFrame) -> None:
    """Free a cached frame, or delete the files of a cut."""
    if hasattr(held, "_componentry_path"):
        release(held)
    else:
        held.unpersist()


def exact_components_local(g: Graph, *, row_cap: int = 5_000_000) -> dict:
    """Union-find on the driver, for tests and tiny graphs: id -> least id. Refuses more than ``row_cap`` edges."""
    if g.edges.limit(row_cap + 1).count() > row_cap:
        raise ValueError(f"over {row_cap} edges")
    sets = DisjointSets()
    for (i,) in g.ids.collect():
        sets.find(i)
    for a, b in g.edges.collect():
        sets.join(a, b)
    return {i: sets.find(i) for i in sets.up}


def recursive_cte_components(edges: DataFrame, depth: int = 8) -> DataFrame:
    """Least id within ``depth`` hops by a recursive SQL query, for tiny graphs; NotConverged if the last hop still lowered a label.

    The engine's recursion has UNION ALL only, so paths are expanded up to the bound.
    """
    spark = edges.sparkSession
    nbrs = cut(adjacency(edges), "cte")
    view = f"_cte_nbrs_{uuid.uuid4().hex}"
    nbrs.createOrReplaceTempView(view)
    found = spark.sql(
        f"""WITH RECURSIVE reach(id, seen, hops) AS (
              SELECT DISTINCT id, id AS seen, 0 FROM {view}
              UNION ALL
              SELECT n.nbr, r.seen, r.hops + 1 FROM reach r JOIN {view} n ON n.id = r.id WHERE r.hops < {int(depth)} AND r.seen < n.nbr)
            SELECT id, min(seen) AS component, min(CASE WHEN hops < {int(depth)} THEN seen END) AS earlier FROM reach GROUP BY id"""
    )
    out = cut(found, "cte")
    spark.catalog.dropTempView(view)
    if not out.where("component < earlier").isEmpty():
        raise NotConverged(f"recursive query: labels still fall at hop {depth}", [])
    return out.select("id", "component")


__all__ = ["exact_components_local", "label_prop_baseline", "recursive_cte_components", "release", "superstep_min"]
