"""Connected components of an undirected link table, by alternating star contractions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import discard, spread_join, written


def _forest(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Replaces the links of each batch by the stars of their local components: never more links than nodes."""
    for pdf in batches:
        parent: dict[int, int] = {}

        def root(x: int) -> int:
            top = x
            while (up := parent.get(top, top)) != top:
                top = up
            while (up := parent.get(x, x)) != top:
                parent[x], x = top, up
            return top

        for a, b in zip(pdf["a"].tolist(), pdf["b"].tolist(), strict=True):
            ra, rb = root(a), root(b)
            if ra != rb:
                parent[max(ra, rb)] = min(ra, rb)
        nodes = [x for x in parent if root(x) != x]
        yield pd.DataFrame({"a": [root(x) for x in nodes], "b": nodes}, dtype="int64")


def _large(edges: DataFrame, n: int) -> DataFrame:
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count("*").alias("w"))
    larger = both.where("b > a")
    return spread_join(larger, least, ["a"], "w", 2 * n).select(F.col("m").alias("a"), "b").where("a < b").distinct()


def _small(edges: DataFrame, n: int) -> DataFrame:
    least = edges.groupBy("b").agg(F.min("a").alias("m"), F.count("*").alias("w"))
    return (
        spread_join(edges, least, ["b"], "w", n)
        .select(F.col("m").alias("a"), F.explode(F.array("a", "b")).alias("b"))
        .where("a < b")
        .distinct()
    )


def connected_components(links: DataFrame) -> DataFrame:
    """(node, component) for every node of `links` (columns a, b: bigint), component being its smallest node.

    Self links and nulls are ignored; an empty table gives an empty result. The state is a
    written table after each round, every round is a fixed number of hash joins and
    map-side-combined minima, and rounds end when the stars no longer change. The links of a node
    with many of them are not gathered: such nodes are few, and their minima are broadcast."""
    edges = links.where("a is not null and b is not null and a <> b").select(
        F.least("a", "b").cast("long").alias("a"), F.greatest("a", "b").cast("long").alias("b")
    )
    edges = written(edges.mapInPandas(_forest, "a long, b long"), "stars")

    def mark(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("a", "b") % 1_000_000_007)).first())

    before = mark(edges)
    while before[0]:
        stars = written(_large(edges, before[0]), "stars")
        n = stars.count()
        edges, old = written(_small(stars, n), "stars"), edges
        discard(old, stars)
        after = mark(edges)
        if after == before:
            break
        before = after
    return edges.select(F.col("b").alias("node"), F.col("a").alias("component")).union(
        edges.select(F.col("a").alias("node"), F.col("a").alias("component")).distinct()
    )
