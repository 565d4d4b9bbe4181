"""Exact links between components: a join of shingle sets on their rarest members.

Two sets that reach a similarity share a shingle among the rarest of each (all but as many as
their overlap needs at least). Shingles whose holders are all of one component cannot join two of
them, so they count as the rarest. Sets that share one are a bucket; large buckets are cut into
chunks, every pair of chunks is a block of its own, and a block counts the overlap of all its
pairs. Nothing is capped: a bucket of m sets of as many components costs m * m / 2 overlaps."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import discard, lean, spread_join, written

#: A chunk's sets and shingles, on average, and the shingles of one overlap product.
CHUNK_SETS, CHUNK_SHINGLES, SLICE = 256, 100_000, 4096


def _tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in (batch.slice(i, 500) for i in range(0, batch.num_rows, 500)):
            sets = [np.frombuffer(m, np.int64) for m in part.column(2).to_pylist()]
            sizes = [len(s) for s in sets]
            item, component = (np.repeat(part.column(i).to_numpy(zero_copy_only=False), sizes) for i in (0, 1))
            flat = np.concatenate(sets) if sets else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(item), pa.array(component), pa.array(flat)], names=["item", "component", "token"])


def _overlaps(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """How many members each of `left` shares with each of `right`."""
    a, b = np.concatenate(left), np.concatenate(right)
    both = np.intersect1d(a, b)
    row_a, row_b = (np.repeat(np.arange(len(s)), [len(x) for x in s]) for s in (left, right))
    at_a, at_b = np.searchsorted(both, a), np.searchsorted(both, b)
    in_a, in_b = (at < len(both) for at in (at_a, at_b))
    in_a[in_a] = both[at_a[in_a]] == a[in_a]
    in_b[in_b] = both[at_b[in_b]] == b[in_b]
    row_a, at_a, row_b, at_b = row_a[in_a], at_a[in_a], row_b[in_b], at_b[in_b]
    out = np.zeros((len(left), len(right)), np.float32)
    for lo in range(0, len(both), SLICE):
        width = min(SLICE, len(both) - lo)
        x, y = np.zeros((len(left), width), np.float32), np.zeros((len(right), width), np.float32)
        ka, kb = (at_a >= lo) & (at_a < lo + width), (at_b >= lo) & (at_b < lo + width)
        x[row_a[ka], at_a[ka] - lo] = 1
        y[row_b[kb], at_b[kb] - lo] = 1
        out += x @ y.T
    return out


def block_links(component: np.ndarray, side: np.ndarray, sets: list[np.ndarray], threshold: int) -> np.ndarray:
    """Pairs of components that a pair of sets of one block links: across the sides, or all pairs if there is one side."""
    if side.min() != side.max():
        left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
    else:
        values, counts = np.unique(component, return_counts=True)
        left, right = np.flatnonzero(component != values[counts.argmax()]), np.arange(len(sets))
    if not len(left):
        return np.empty((0, 2), np.int64)
    size = np.array([len(s) for s in sets], np.int64)
    common = _overlaps([sets[i] for i in left], [sets[i] for i in right]).astype(np.int64)
    union = size[left][:, None] + size[right][None, :] - common
    i, j = np.nonzero((100 * common >= threshold * union) & (common > 0) & (component[left][:, None] != component[right][None, :]))
    a, b = component[left][i], component[right][j]
    return np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0)


def _blocks(threshold: int) -> Callable:
    """Links of the blocks of one sorted partition, one block in memory at a time."""

    def links(rows: pa.Table) -> pa.RecordBatch:
        component, side = rows.column("component").to_numpy(), rows.column("side").to_numpy()
        sets = [np.frombuffer(m, np.uint64) for m in rows.column("members").to_pylist()]
        got = block_links(component, side, sets, threshold)
        return pa.RecordBatch.from_arrays([pa.array(got[:, 0].copy()), pa.array(got[:, 1].copy())], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        last = None
        for batch in batches:
            keys = np.stack([batch.column(c).to_numpy().astype("int64") for c in ("key", "i", "j")], axis=1)
            starts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1), len(keys)]
            for lo, hi in zip(starts, starts[1:], strict=False):
                if hi == lo:
                    continue
                key = tuple(keys[lo])
                if key != last and held:
                    yield links(pa.Table.from_batches(held))
                    held = []
                held.append(batch.slice(lo, hi - lo))
                last = key
        if held:
            yield links(pa.Table.from_batches(held))

    return run


def component_links(crowd: DataFrame, sets: DataFrame, threshold: int) -> DataFrame:
    """(a, b) for all pairs of components of `crowd` (did, component) with members that reach the similarity.

    `sets` has (did, members), members being sorted distinct 64-bit values; a did may have several sets."""
    items = (
        crowd.select("did", "component").distinct().join(sets, "did")
        .withColumn("digest", F.xxhash64("members"))
        .groupBy("did", "component", "digest")
        .agg(F.first("members").alias("members"))
        .select(F.monotonically_increasing_id().alias("item"), "component", "members")
    )
    items = written(items.where("length(members) > 0"), "items")
    tokens = items.mapInArrow(lean(_tokens), "item long, component long, token long")
    # the holders' digest is the bucket: shingles that the same sets hold need one only
    held = items.count()
    live = (
        tokens.groupBy("token")
        .agg(F.count("*").alias("df"), F.min("component").alias("lo"), F.max("component").alias("hi"), F.bit_xor(F.xxhash64("item")).alias("key"))
        .where("lo <> hi")
        .select("token", "df", "key")
    )
    n = F.expr("cast(length(members) div 8 as bigint)")
    ranked = (
        spread_join(tokens.select("item", "token"), live, ["token"], "df", held)
        .groupBy("item").agg(F.sort_array(F.collect_list(F.struct("df", "key"))).alias("live"))
        .join(items.select("item", "component", n.alias("n")), "item")
        .withColumn("keep", F.expr(f"cast(size(live) - (n * {threshold} + 99) div 100 + 1 as int)"))
        .where("keep > 0")
    )
    postings = written(
        ranked.select("item", "component", "n", F.explode(F.expr("array_distinct(transform(slice(live, 1, keep), x -> x.key))")).alias("key")),
        "postings",
    )
    parts = postings.groupBy("key", "component").agg(
        F.count("*").alias("m"), F.sum("n").alias("w"), F.bit_xor(F.xxhash64("item")).alias("x"), F.bit_xor(F.xxhash64("item", F.lit(1))).alias("y")
    )
    buckets = (
        parts.groupBy("key")
        .agg(F.count("*").alias("kinds"), F.sum("m").alias("m"), F.sum("w").alias("w"), F.max(F.struct("m", "w", "component")).alias("top"), F.bit_xor("x").alias("x"), F.bit_xor("y").alias("y"))
        .where("kinds > 1")
        .groupBy("m", "x", "y")
        .agg(F.min(F.struct("key", "w", "top")).alias("b"))
        .select(
            "b.key",
            F.col("b.top.component").alias("most"),
            "m",
            F.expr(f"m <= {CHUNK_SETS} and b.w <= {CHUNK_SHINGLES}").alias("whole"),
            F.expr(f"cast(greatest(ceil((m - b.top.m) / {CHUNK_SETS}), ceil((b.w - b.top.w) / {CHUNK_SHINGLES})) as int)").alias("rest"),
            F.expr(f"cast(greatest(ceil(b.top.m / {CHUNK_SETS}), ceil(b.top.w / {CHUNK_SHINGLES})) as int)").alias("tops"),
        )
    )
    # chunks of the largest component meet those of the others only, which also meet each other
    place = F.expr("""CASE WHEN whole THEN array(named_struct('i', 0, 'j', 0, 'side', 0))
        WHEN component = most THEN transform(sequence(0, rest - 1), s -> named_struct('i', s, 'j', rest + salt, 'side', 1))
        ELSE concat(transform(sequence(0, rest - 1), s -> named_struct('i', least(s, salt), 'j', greatest(s, salt), 'side', if(s < salt, 1, 0))),
                    transform(sequence(0, tops - 1), g -> named_struct('i', salt, 'j', rest + g, 'side', 0))) END""")
    placed = (
        spread_join(postings.select("item", "component", "key"), buckets, ["key"], "m", held)
        .withColumn("salt", F.expr("cast(pmod(xxhash64(item, key, 2), if(component = most, tops, rest)) as int)"))
        .select("item", "component", "key", F.explode(place).alias("at"))
        .select("item", "component", "key", "at.i", "at.j", "at.side")
        .join(items.select("item", "members"), "item")
        .select("component", "key", "i", "j", "side", "members")
    )
    blocks = placed.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")
    found = written(blocks.mapInArrow(lean(_blocks(threshold)), "a long, b long").distinct(), "joined")
    discard(items, postings)
    return found
