"""Merge functions: what a set of references makes of its members' distributions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: name -> (column of recorded probabilities, number of member pairs) -> aggregate column
MERGES: dict[str, Callable[[Column, Column], Column]] = {}


def register_merge(name: str, build: Callable[[Column, Column], Column]) -> None:
    MERGES[name] = build


register_merge("average", lambda p, n: F.sum(p) / F.first(n))
register_merge("recorded", lambda p, n: F.avg(p))
register_merge("disjunct", lambda p, n: 1 - F.product(1 - p))
register_merge("max", lambda p, n: F.max(p))


def noisy_or(weight: float) -> Callable[[Column, Column], Column]:
    """A merge in which each recorded pair is a cause that takes effect with ``weight``; at 1 it is the disjunction."""
    return lambda p, n: 1 - F.product(1 - F.lit(weight) * p)


register_merge("noisy_or", noisy_or(0.8))
