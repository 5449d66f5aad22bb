"""The round framework: start state, hash step, merge step, until nothing changes.

Each round is one query whose result is cut to files. Row counts and an order-free fingerprint come from
observed metrics of that same query, so the stop test needs no second pass.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from componentry.functions.graphs import Graph, adjacency
from componentry.operators import emit
from componentry.plans.storage import cut, release, sweep
from componentry.schemas import ROUND_STATS


#: rows of a state from which the exchange files of a round are dropped after it
SWEEP_ROWS = 1_000_000


class NotConverged(RuntimeError):
    """The round limit or a size cap was reached: the run did not finish (DNF)."""

    def __init__(self, why: str, stats: list[dict]):
        super().__init__(why)
        self.stats = stats


@dataclass
class RunResult:
    """``components``: (id, component) with component = the least id of it."""

    components: DataFrame
    stats: list[dict]
    meta: dict = field(default_factory=dict)

    def stats_frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(s.get(f.name) for f in ROUND_STATS) for s in self.stats], ROUND_STATS)

    @property
    def rounds_run(self) -> int:
        return sum(s["round"] > 0 for s in self.stats)

    @property
    def rounds_productive(self) -> int:
        return sum(s["round"] > 0 and s["changed"] for s in self.stats)

    @property
    def peak_state_rows(self) -> int:
        return max((s["state_rows"] for s in self.stats), default=0)

    @property
    def peak_messages(self) -> int:
        return max((s["messages_emitted"] for s in self.stats), default=0)


def init_self(ids: DataFrame) -> DataFrame:
    """Each id holds itself."""
    return ids.select(F.col("id").alias("key"), F.col("id").alias("member"))


def init_closed(g: Graph) -> DataFrame:
    """Each id holds itself and its neighbours: V + 2E rows, without a pass of its own for the ids that edges touch."""
    two = emit.pairs(g.edges, ("src", "dst"), ("dst", "src"), ("src", "src"), ("dst", "dst"))
    return two if g.vertices is None else two.unionByName(init_self(g.ids))


class Loop:
    """Runs rounds over a state and records their measures.

    ``detect``: ``fingerprint`` (row count and sum of row hashes) or ``exact`` (a set difference with the
    state before). ``row_cap`` ends a run whose state or messages grow past it.
    """

    def __init__(self, run: str, *, max_rounds: int = 64, detect: str = "fingerprint", row_cap: int | None = None, stats: bool = True):
        self.run, self.max_rounds, self.detect, self.row_cap, self.counts = run, max_rounds, detect, row_cap, stats
        self.stats: list[dict] = []
        self.state: DataFrame | None = None
        self.largest = 0  # most rows of a key, where the state has ``size``
        self._print: tuple = ()
        self._round = 0

    @property
    def rounds(self) -> int:
        return sum(s["round"] > 0 for s in self.stats)

    def materialise(self, state: DataFrame, messages: Observation | None, phase: str, compare: bool = True, judged: str = "key, member") -> bool:
        """Cut ``state``; True if it differs from the last state compared."""
        began = time.perf_counter()
        seen = Observation(uuid.uuid4().hex)
        cols = [c.strip() for c in judged.split(",")]
        sizes = [F.coalesce(F.max("size"), F.lit(0).cast("long")).alias("m")] if "size" in state.columns else []
        observed = state.observe(seen, *sizes, F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.xxhash64(*cols).cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)")).alias("h"))
        before, self.state = self.state, cut(observed, self.run)
        got = self._read(seen)
        self.largest = got.get("m", 0)
        mark = (got["n"], got["h"])
        if self.detect == "exact" and before is not None and compare:
            a, b = before.select(*cols), self.state.select(*cols)
            changed = not (a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty())
        else:
            changed = mark != self._print
        if compare:
            self._print = mark
        sent = 0 if not got["n"] else self._read(messages)["n"] if messages is not None else got["n"]
        self.stats.append({"run": self.run, "round": self._round, "phase": phase, "messages_emitted": sent, "state_rows": got["n"], "changed": changed, "seconds": round(time.perf_counter() - began, 3)})
        release(before)
        if got["n"] > SWEEP_ROWS:
            sweep(self.state.sparkSession)
        if self.row_cap is not None and got["n"] > self.row_cap:
            raise NotConverged(f"{self.run}: {got['n']} state rows; the cap is {self.row_cap}", self.stats)
        return changed

    def _read(self, seen: Observation) -> dict:
        """Observed metrics; a plan that turns out empty is replaced at run time, and reports none."""
        try:
            return seen.get
        except Py4JError:
            if not self.state.isEmpty():
                raise
            return {"n": 0, "h": 0}

    def start(self, state: DataFrame, phase: str = "init") -> None:
        self._round = 0
        self._print = ()
        self.materialise(state, None, phase)

    def counted(self, messages: DataFrame) -> tuple[DataFrame, Observation | None]:
        if not self.counts:
            return messages, None
        seen = Observation(uuid.uuid4().hex)
        return messages.observe(seen, F.count(F.lit(1)).alias("n")), seen

    def step(self, send: Callable[[DataFrame], DataFrame], merge: Callable[[DataFrame], DataFrame], phase: str = "round", compare: bool = True) -> bool:
        if self.stats and not self.stats[-1]["state_rows"]:
            return False  # nothing to do on an empty graph
        if self._round >= self.max_rounds:
            raise NotConverged(f"{self.run}: no end after {self._round} rounds", self.stats)
        self._round += 1
        messages, seen = self.counted(send(self.state))
        return self.materialise(merge(messages), seen, phase, compare)

    def until_stable(self, send: Callable, merge: Callable, phase: str = "round", after: Callable[[Loop], bool] | None = None) -> None:
        """Rounds of one kind until the state stays as it is, or ``after`` says stop."""
        while self.step(send, merge, phase):
            if after is not None and after(self):
                return


def export_owner_clusters(state: DataFrame) -> DataFrame:
    """A key that is its own least member owns a component; what it holds are the members."""
    return state.where("key = owner").select(F.col("member").alias("id"), F.col("key").alias("component"))


def export_by_label(state: DataFrame) -> DataFrame:
    """Least member of each key."""
    return state.groupBy(F.col("key").alias("id")).agg(F.min("member").alias("component"))


def original_order(components: DataFrame, book: DataFrame) -> DataFrame:
    """Components over ranks as components over ids, named by their least id."""
    named = components.join(book.withColumnRenamed("id", "orig"), components["id"] == book["rank"]).select("orig", "component")
    least = named.groupBy("component").agg(F.min("orig").alias("least"))
    return named.join(least, "component").select(F.col("orig").alias("id"), F.col("least").alias("component"))


__all__ = ["Graph", "Loop", "NotConverged", "RunResult", "adjacency", "export_by_label", "export_owner_clusters", "init_closed", "init_self", "original_order"]
