"""Criteria that choose one coordinating set among several. Ties go to the least order columns."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Selection:
    score: str | None = "n"
    must: int | None = None

    def pick(self, sets: DataFrame, order: list[str]) -> DataFrame:
        """At most one row of ``sets`` (columns n, weight, ids and the order columns)."""
        left = sets.where(F.array_contains("ids", F.lit(self.must))) if self.must is not None else sets
        by = [F.col(self.score).desc()] if self.score else []
        return left.orderBy(*by, *order).limit(1)  # one row per task reaches the driver

    def ranked(self, sets: DataFrame, order: list[str], k: int) -> DataFrame:
        by = [F.col(self.score).desc()] if self.score else []
        return sets.orderBy(*by, *order).limit(k)


def largest() -> Selection:
    return Selection("n")


def most_weight() -> Selection:
    return Selection("weight")


def containing(qid: int) -> Selection:
    return Selection("n", qid)


def first() -> Selection:
    """The first set in order, whatever its size."""
    return Selection(None)
