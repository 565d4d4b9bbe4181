"""Table and aggregate functions over ordered groups."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F


@F.udtf(returnType="k string, runs bigint, n bigint")
class RunsOf:
    """Runs of the third column in a group of (key, order, value) rows that come in order."""

    def __init__(self) -> None:
        self.key, self.last, self.runs, self.n = None, None, 0, 0

    def eval(self, row: Row) -> None:
        self.runs += int(self.n == 0 or row[2] != self.last)
        self.key, self.last, self.n = row[0], row[2], self.n + 1

    def terminate(self) -> Iterator[tuple]:
        if self.n:
            yield self.key, self.runs, self.n


def register_table_functions(spark: SparkSession) -> None:
    spark.udtf.register("runs_of", RunsOf)


@F.pandas_udf("long")
def group_runs(order: pd.Series, value: pd.Series) -> int:
    """Runs of a group's values in the order of `order`; a group must fit a task."""
    v = value.iloc[order.argsort(kind="stable")].reset_index(drop=True)
    if not len(v):
        return 0
    same = (v == v.shift()) | (v.isna() & v.shift().isna())
    return int((~same.iloc[1:]).sum()) + 1
