"""Stop tests of single linkage: local (each cluster is judged alone) and monotone (once stopped, larger clusters are)."""

from __future__ import annotations

import itertools
import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


class NonLocalStopError(ValueError):
    """The test needs to know other clusters."""


@dataclass(frozen=True)
class Stop:
    """``__call__(size, nearest)``: size of a cluster and distance of the nearest cluster outside (inf: none)."""

    def __call__(self, size: int, nearest: float) -> bool:
        raise NotImplementedError

    def column(self, size: Column, nearest: Column) -> Column:
        """The test over columns: a worker's call for each row, unless the kind of test has an expression for it."""
        return F.udf(lambda s, d: bool(self(int(s), float(d))), T.BooleanType())(size, nearest)


@dataclass(frozen=True)
class DistanceStop(Stop):
    """Stopped when nothing outside is within ``theta``."""

    theta: float

    def __call__(self, size: int, nearest: float) -> bool:
        return nearest > self.theta

    def column(self, size: Column, nearest: Column) -> Column:
        return nearest > self.theta


@dataclass(frozen=True)
class SizeStop(Stop):
    """Stopped at ``k`` members."""

    k: int

    def __call__(self, size: int, nearest: float) -> bool:
        return size >= self.k

    def column(self, size: Column, nearest: Column) -> Column:
        return size >= self.k


@dataclass(frozen=True)
class LocalStop(Stop):
    """Any predicate of (size, nearest)."""

    fn: Callable[[int, float], bool]

    def __call__(self, size: int, nearest: float) -> bool:
        return bool(self.fn(size, nearest))


def cluster_count_stop(k: int) -> Stop:
    """Refused: the number of clusters is not known to a cluster."""
    raise NonLocalStopError("a cluster cannot tell how many clusters there are; use a distance or size test")


def check_monotone(stop: Stop, sizes: range = range(1, 30), distances: tuple = (0.0, 0.1, 0.25, 0.5, 1.0, 2.0, math.inf)) -> None:
    """ValueError if some cluster is stopped and a larger one, whose nearest is no nearer, is not."""
    for (s1, d1), (s2, d2) in itertools.product(itertools.product(sizes, distances), repeat=2):
        if s2 >= s1 and d2 >= d1 and stop(s1, d1) and not stop(s2, d2):
            raise ValueError(f"not monotone: stopped at size {s1}, distance {d1}, not at {s2}, {d2}")
