"""Near duplicates by an LSH forest: several sorted signature orders, candidates among
longest-common-prefix neighbours with a depth that adapts to each region, links confirmed on
full shingle sets, and components of the confirmed links.

Scale notes. Equal shingle sets collapse before any pairing, through a map-side-combined
minimum. Regions of one document never leave the first count. What is paired is sorted by a
range exchange, so a dense region is cut over tasks; a document meets a bounded number of
neighbours in each order, and the members of a dense region the best-linked one. What is left of
regions with several components is joined exactly (`setjoin`), which is complete (so neighbours
that a task's border parts are found there) and costs the square of a bucket of sets that share a
rare shingle and no component. Frequent keys are dealt over tasks (`spread_join`), no group is
gathered in one task, and nothing that grows with the corpus goes to the driver. Rows that cannot
have a partner in a join are left out before they are dealt (`sieve`, a broadcast table of bounded
size); beyond some 40 million keys a join it lets most rows through, and they are all dealt."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.components import connected_components
from rowloom.llm.setjoin import component_links
from rowloom.llm.shared import discard, lean, sieve, sifted, spread_join, utf8, written
from rowloom.llm.shingles import WordHasher, shingle_set, split_words

#: Hash functions; hashes of a full sorted key after those of the region's key.
HASHES, REST = 128, 5
#: Regions up to this size are paired fully; in larger ones, neighbours within REACH.
SMALL, REACH = 16, 2
#: A pair at the threshold shares no region, or fails the sketch bound, with at most these probabilities.
MISS, SKETCH_MISS = 8e-7, 2e-8


def forest(threshold: int) -> tuple[int, int]:
    """Trees and hashes in a region's key: the longest key (8 at most) whose trees fit the hashes."""
    if not 1 <= threshold <= 100:
        raise ValueError("threshold must be within 1 and 100")
    for root in range(8, 0, -1):
        miss = 1 - (threshold / 100) ** root
        trees = max(1, math.ceil(math.log(MISS) / math.log(miss))) if miss > 0 else 1
        if trees * root <= HASHES:
            return trees, root
    raise ValueError(f"a threshold of {threshold} needs more than {HASHES} hashes")


def sketch_bound(threshold: int) -> int:
    """One-bit sketch positions of `HASHES` that must agree."""
    p = (1 + threshold / 100) / 2
    below = 0.0
    for k in range(HASHES):
        below += math.comb(HASHES, k) * p**k * (1 - p) ** (HASHES - k)
        if below > SKETCH_MISS:
            return k
    return HASHES


_SEEDS = np.random.default_rng(20_240_607).integers(1, 2**62, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BLOCK = 1 << 18


def minhash(sets: list[np.ndarray]) -> np.ndarray:
    """Signatures, one row of `HASHES` unsigned 32-bit minima for each set (empty sets: all ones)."""
    out = np.full((len(sets), HASHES), 0xFFFFFFFF, np.uint32)
    at = 0
    while at < len(sets):
        end, n = at, 0
        while end < len(sets) and (n == 0 or n + len(sets[end]) <= _BLOCK):
            n += len(sets[end])
            end += 1
        rows = [i for i in range(at, end) if len(sets[i])]
        if rows:
            flat = np.concatenate([sets[i] for i in rows])
            starts = np.cumsum([0, *(len(sets[i]) for i in rows[:-1])])
            for k in range(HASHES):
                out[rows, k] = np.minimum.reduceat((flat * _SEEDS[k]) >> np.uint64(32), starts)
        at = end
    return out


def _one_bit(sig: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    bits = np.packbits((sig ^ (sig >> np.uint32(16))) & np.uint32(1), axis=1).view(">i8")
    return bits[:, 0].astype("int64"), bits[:, 1].astype("int64")


def _digest(width: int) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = WordHasher()
        for batch in batches:
            for part in (batch.slice(i, 1000) for i in range(0, batch.num_rows, 1000)):
                sets = [shingle_set(split_words(t), hasher, width) for t in part.column(1).to_pylist()]
                sig = minhash(sets)
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column(0),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array([xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets], pa.binary()),
                        pa.array([r.tobytes() if len(s) else None for r, s in zip(sig, sets, strict=True)], pa.binary()),
                    ],
                    names=["doc_id", "n_shingles", "set_key", "signature"],
                )

    return run


def _orders(trees: int, root: int) -> Callable:
    """A row for each document and tree: region key, the rest of the sorted key, sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 2000) for i in range(0, batch.num_rows, 2000)):
                n = part.num_rows
                sig = np.frombuffer(b"".join(part.column(2).to_pylist()), np.uint32).reshape(n, HASHES)
                s1, s2 = _one_bit(sig)
                ids, size = part.column(0).to_numpy(zero_copy_only=False), part.column(1).to_numpy(zero_copy_only=False)
                region, rest = [], []
                for t in range(trees):
                    at = [(t * root + i) % HASHES for i in range(root + REST)]
                    head = np.ascontiguousarray(sig[:, at[:root]])
                    region += [xxhash.xxh3_64_intdigest(r.tobytes(), t) - (1 << 63) for r in head]
                    rest += [r.tobytes() for r in sig[:, at[root:]].astype(">u4")]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.repeat(np.arange(trees, dtype="int32"), n)),
                        pa.array(region, pa.int64()),
                        pa.array(rest, pa.binary()),
                        *(pa.array(np.tile(x.astype("int64"), trees)) for x in (ids, size, s1, s2)),
                    ],
                    names=["tree", "region", "rest", "did", "n", "s1", "s2"],
                )

    return run


_BITS = np.array([bin(i).count("1") for i in range(1 << 16)], np.uint8)


def _agree(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return 64 - _BITS[(x ^ y).view(np.uint16).reshape(-1, 4)].sum(axis=1, dtype=np.int64)


def _neighbours(threshold: int) -> Callable:
    """Candidates among the rows of one sorted partition (all rows of a small region are in it)."""
    root, bound = forest(threshold)[1], sketch_bound(threshold)
    deep = root + REST

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        kept = 0

        def pairs(rows: pa.Table, fresh: int) -> pa.RecordBatch:
            """Pairs whose later row is at `fresh` or after it."""
            n = rows.num_rows
            tree, region, did, size, s1, s2 = (
                rows.column(c).to_numpy().astype("int64") for c in ("tree", "region", "did", "n", "s1", "s2")
            )
            rest = np.frombuffer(b"".join(rows.column("rest").to_pylist()), ">u4").reshape(n, REST)
            same = (tree[1:] == tree[:-1]) & (region[1:] == region[:-1])
            lcp = np.where(same, root + np.cumprod(rest[1:] == rest[:-1], axis=1).sum(axis=1), 0)
            run_size = {}
            for depth in range(root, deep + 1):
                run_id = np.concatenate([[0], np.cumsum(lcp < depth)])
                run_size[depth] = np.bincount(run_id)[run_id]
            a, b = [np.empty(0, "int64")], [np.empty(0, "int64")]
            common = lcp.copy()
            for o in range(1, SMALL):
                if o > 1:
                    common = np.minimum(common[:-1], lcp[o - 1 :])
                i = np.flatnonzero(common >= root)
                i = i[i + o >= fresh]
                if o > REACH and len(i):
                    run = np.choose(common[i] - root, [run_size[d][i] for d in range(root, deep + 1)])
                    i = i[run <= SMALL]
                if len(i):
                    j = i + o
                    close = np.minimum(size[i], size[j]) * 100 >= threshold * np.maximum(size[i], size[j])
                    close &= (did[i] != did[j]) & (_agree(s1[i], s1[j]) + _agree(s2[i], s2[j]) >= bound)
                    a.append(np.minimum(did[i], did[j])[close])
                    b.append(np.maximum(did[i], did[j])[close])
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], names=["a", "b"])

        tail: pa.Table | None = None
        for batch in batches:
            held.append(batch)
            kept += batch.num_rows
            if kept >= 50_000:
                rows = pa.Table.from_batches(held)
                rows = rows if tail is None else pa.concat_tables([tail, rows])
                yield pairs(rows, 0 if tail is None else tail.num_rows)
                tail, held, kept = rows.slice(max(0, rows.num_rows - 2 * SMALL)).combine_chunks(), [], 0
        if held:
            rows = pa.Table.from_batches(held)
            rows = rows if tail is None else pa.concat_tables([tail, rows])
            yield pairs(rows, 0 if tail is None else tail.num_rows)

    return run


def _sets(width: int) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = WordHasher()
        for batch in batches:
            for part in (batch.slice(i, 1000) for i in range(0, batch.num_rows, 1000)):
                sets = [shingle_set(split_words(t), hasher, width).tobytes() for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.binary())], names=["did", "members"])

    return run


def _confirm(pairs: DataFrame, sets: DataFrame, threshold: int) -> DataFrame:
    """Pairs whose full sets reach the similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * common >= threshold * (len(x) + len(y) - common) > 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    sets = sifted(sets, pairs.select(F.explode(F.array("a", "b")).alias("did")), ["did"])
    left = sets.select(F.col("did").alias("a"), F.col("members").alias("x"))
    right = sets.select(F.col("did").alias("b"), F.col("members").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(lean(run), "a long, b long")


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, threshold: int = 85
) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of `docs`.

    Documents are linked when 100 * |A n B| >= threshold * |A u B| over their sets of distinct
    `width`-word shingles (lower-cased A-Z; words end at white space). A text of fewer words is
    one shingle; null, empty and blank texts have none and stay alone. `component_id` is the
    smallest id reachable. Rows that repeat an id are one node. A null id is no node: its
    component_id is null and it is kept. Extra columns are ignored. Orders and bounds
    follow from `threshold`; below 11 they need too many hashes, which is a ValueError."""
    forest(threshold)  # refuses thresholds that it cannot serve before any work
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text"))
    base = written(
        texts.mapInArrow(lean(_digest(width)), "doc_id long, n_shingles long, set_key binary, signature binary"), "digests"
    )
    own = base.where("set_key is not null and doc_id is not null")
    n_docs = own.count()
    copies = written(
        own.groupBy("set_key").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("copies")).where("copies > 1"), "copies"
    )
    # only rows that may have a copy are dealt by their set
    marked = sieve(own.select("doc_id", "n_shingles", "set_key", "signature"), copies.select("set_key"), ["set_key"])
    leads = (
        spread_join(marked.where("__hit").drop("__hit"), copies, ["set_key"], "copies", n_docs, outer=True)
        .where("first_id is null or first_id = doc_id")
        .select("doc_id", "n_shingles", "signature")
        .union(marked.where("not __hit").select("doc_id", "n_shingles", "signature"))
    )
    trees, root = forest(threshold)
    rows = leads.mapInArrow(lean(_orders(trees, root)), "tree int, region long, rest binary, did long, n long, s1 long, s2 long")
    sizes = written(rows.groupBy("tree", "region").agg(F.count("*").alias("region_rows")).where("region_rows > 1"), "sizes")
    # at most HEAVY frequent regions in each tree
    spots = ["tree", "region"]
    shared = written(spread_join(sifted(rows, sizes.select(spots), spots), sizes, spots, "region_rows", n_docs), "regions")

    order = ["tree", "region", "rest", "did"]
    cols = ["tree", "region", "rest", "did", "n", "s1", "s2"]
    small = shared.where(F.col("region_rows") <= SMALL).select(cols).repartition("tree", "region")
    dense = shared.where(F.col("region_rows") > SMALL)
    found = small.sortWithinPartitions(*order).mapInArrow(lean(_neighbours(threshold)), "a long, b long")
    crowd = dense.select(cols).repartitionByRange(*order).sortWithinPartitions(*order)
    found = written(found.union(crowd.mapInArrow(lean(_neighbours(threshold)), "a long, b long")).distinct(), "candidates")

    # a row for each document, with its dense regions: one a tree at most
    members = written(
        dense.groupBy("did").agg(*[F.first(c).alias(c) for c in ("n", "s1", "s2")], F.collect_set(F.struct("tree", "region")).alias("spots")), "dense"
    )
    needed = written(found.select(F.explode(F.array("a", "b")).alias("did")).union(members.select("did")).distinct(), "needed")
    # both sides are dealt by id at every size, so that cost grows with the input
    wanted = sifted(texts.withColumnRenamed("doc_id", "did"), needed, ["did"])
    sets = written(
        wanted.join(needed.hint("merge"), "did", "left_semi").mapInArrow(lean(_sets(width)), "did long, members binary"),
        "sets",
    )
    discard(sizes, shared, needed)
    near = written(_confirm(found, sets, threshold), "links")
    nodes = written(connected_components(near), "nodes")

    hubbed = written(_hub_pairs(members, near, nodes, threshold, n_docs), "hub_pairs")
    links = written(near.union(_confirm(hubbed, sets, threshold)).distinct(), "links")
    again = written(connected_components(links), "nodes")
    discard(found, near, nodes, hubbed)

    mixed = written(_mixed(members, again, n_docs), "mixed")
    more = written(component_links(mixed, sifted(sets, mixed.select("did"), ["did"]), threshold), "links")
    nodes = written(connected_components(links.union(more)), "nodes")
    discard(members, sets, links, again, mixed, more)

    # rows without a set or an id are alone
    alone = base.where("set_key is null or doc_id is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    grouped = (
        spread_join(own.select("doc_id", "n_shingles", "set_key"), copies, ["set_key"], "copies", n_docs, outer=True)
        .select("doc_id", "n_shingles", F.coalesce("first_id", "doc_id").alias("node"))
    )
    # a node is as frequent as its set
    weights = copies.groupBy(F.col("first_id").alias("node")).agg(F.sum("copies").alias("w"))
    named = nodes.join(weights, "node", "left").withColumn("w", F.coalesce("w", F.lit(1)))
    linked = spread_join(grouped, named, ["node"], "w", n_docs, outer=True).select(
        "doc_id", "n_shingles", F.coalesce("component", "node").alias("component_id")
    )
    return linked.union(alone).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def _mixed(members: DataFrame, nodes: DataFrame, n_docs: int) -> DataFrame:
    """(did, component) of the members of dense regions that hold more than one component."""
    labelled = members.join(nodes.withColumnRenamed("node", "did"), "did", "left").select(
        F.explode("spots").alias("at"), "did", F.coalesce("component", "did").alias("component")
    ).select("at.tree", "at.region", "did", "component")
    regions = (
        labelled.groupBy("tree", "region")
        .agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("w"))
        .where("lo <> hi")
    )
    return spread_join(labelled, regions, ["tree", "region"], "w", n_docs).select("did", "component").distinct()


def _hub_pairs(members: DataFrame, links: DataFrame, nodes: DataFrame, threshold: int, n_docs: int) -> DataFrame:
    """Members of dense regions against the best-linked member of their region if it is in another component."""
    degree = links.select(F.explode(F.array("a", "b")).alias("did")).groupBy("did").agg(F.count("*").alias("degree"))
    labelled = (
        members.join(degree, "did", "left")
        .join(nodes.withColumnRenamed("node", "did"), "did", "left")
        .select(F.explode("spots").alias("at"), "did", "n", "s1", "s2", F.coalesce("degree", F.lit(0)).alias("degree"), F.coalesce("component", "did").alias("component"))
        .select("at.tree", "at.region", "did", "n", "s1", "s2", "degree", "component")
    )
    best = labelled.groupBy("tree", "region").agg(
        F.expr("max_by(struct(did, n, s1, s2, component), struct(degree, -did))").alias("h"), F.count("*").alias("w")
    )
    agree = F.lit(128) - F.bit_count(F.col("s1").bitwiseXOR(F.col("h.s1"))) - F.bit_count(F.col("s2").bitwiseXOR(F.col("h.s2")))
    close = F.least("n", "h.n") * 100 >= F.greatest("n", "h.n") * threshold
    return (
        spread_join(labelled, best, ["tree", "region"], "w", n_docs)
        .where((F.col("component") != F.col("h.component")) & close & (agree >= sketch_bound(threshold)))
        .select(F.least("did", "h.did").alias("a"), F.greatest("did", "h.did").alias("b"))
        .distinct()
    )
