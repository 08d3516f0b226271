"""Functions for SQL: scalar ones that Catalyst inlines, an aggregate and a table function."""

from __future__ import annotations

from typing import Any

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    """lectic_less(a, b), lectic_less_at(a, b, p), seed_of(d, p) on one-word sets, mine_concepts(TABLE)
    and mine_concepts_by_day(TABLE ... PARTITION BY day)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lectic_less(a BIGINT, b BIGINT) RETURNS BOOLEAN RETURN a < b")
    above = "(9223372036854775807 ^ (shiftleft(1L, 63 - p) - 1L))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lectic_less_at(a BIGINT, b BIGINT, p INT) RETURNS BOOLEAN RETURN IF(p = 0, true, (a & {above}) = (b & {above})) AND (b & shiftleft(1L, 62 - p)) <> 0 AND (a & shiftleft(1L, 62 - p)) = 0")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION seed_of(d BIGINT, p INT) RETURNS BIGINT RETURN IF(p = 0, 0L, d & {above}) | shiftleft(1L, 62 - p)")
    spark.udtf.register("mine_concepts", F.udtf(MineConcepts, returnType="intent string, size int, support bigint"))
    spark.udtf.register("mine_concepts_by_day", F.udtf(MineConceptsByDay, returnType="day string, intent string, size int, support bigint"))


def intersect_agg(column: str) -> Column:
    """An aggregate: what all sets (ARRAY<STRING>) of a group share."""

    def shared(sets):
        kept = None
        for s in sets:
            kept = set(s) if kept is None else kept & set(s)
        return sorted(kept or ())

    shared.__annotations__ = {"sets": pd.Series, "return": Any}
    return F.pandas_udf(shared, "array<string>")(column)


class MineConcepts:
    """A table function over rows with a column attrs: all concepts of each partition of its input.

    The distinct rows of a partition are held in memory; partitions are meant to be groups of moderate
    size, such as a region or a day."""

    def __init__(self):
        self._rows: dict[frozenset, int] = {}

    def eval(self, row):
        key = frozenset(row["attrs"])
        self._rows[key] = self._rows.get(key, 0) + 1

    def terminate(self):
        everything = frozenset().union(*self._rows) if self._rows else frozenset()
        family, fresh = {everything}, {everything}
        for row in self._rows:
            fresh = {f & row for f in family} - family
            family |= fresh
        for f in family:
            support = sum(n for r, n in self._rows.items() if f <= r)
            yield ",".join(sorted(x.replace("\\", "\\\\").replace(",", "\\,") for x in f)), len(f), support


class MineConceptsByDay(MineConcepts):
    """The same over rows with columns day and attrs, partitioned by the day, which every concept carries."""

    def __init__(self):
        super().__init__()
        self._day: str | None = None

    def eval(self, row):
        self._day = row["day"]
        super().eval(row)

    def terminate(self):
        for concept in super().terminate():
            yield self._day, *concept
