"""Block-parallel reordering: tours, list walks and improvements inside horizontal blocks of an order.

A kernel sees one block's code matrix and gives a permutation; the rows move with all their
columns as Arrow arrays, so types and nulls stay as they are."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rowloom.operators.dictionary import build_dictionary, column_order, encode
from rowloom.operators.kernels import distance as D
from rowloom.operators.kernels import improve as I
from rowloom.operators.kernels import lists as L
from rowloom.operators.kernels import tours as C
from rowloom.operators.order import order_by
from rowloom.operators.position import assign_blocks, numbered

Kernel = Callable[[np.ndarray, int], np.ndarray]
BLOCK_ROWS = 131_072
TOUR_ROWS = 4096
#: Rows of the largest table that one walk takes as a whole.
WHOLE_ROWS = 1 << 22


def _start(codes: np.ndarray, start: str | int, seed: int, before: np.ndarray | None) -> int:
    if start == "random":
        return int(np.random.default_rng(seed).integers(len(codes)))
    if start == "nearest_to_prev" and before is not None:
        return int(D.to_one(codes, before).argmin())
    return int(start) if isinstance(start, int) else 0


def kernel(name: str, start: str | int = "first", k: int | None = None, lists: str | list[list[int]] = "rotations", reuse_sort: bool = True, gray: bool = False, **opt) -> Callable:  # noqa: ANN003
    """A function (codes, seed, row before the block) -> permutation, for every block method."""

    def run(codes: np.ndarray, seed: int = 0, before: np.ndarray | None = None) -> np.ndarray:
        if len(codes) < 2:
            return np.arange(len(codes))
        at = _start(codes, start, seed, before)
        if name == "multiple_lists":
            return L.walk(codes, L.list_orders(codes.shape[1], k, lists), at, reuse_sort, gray)
        if name == "nearest_neighbor":
            return C.nearest_neighbor(codes, at, **opt)
        if name == "savings":
            return C.savings(codes, seed=seed, **{"depot": at, **opt})
        if name == "insertion":
            return C.insertion(codes, start=at, seed=seed, **opt)
        if name == "multiple_fragment":
            return C.multiple_fragment(codes, **opt)
        if name == "iterated_matching":
            return C.iterated_matching(codes)
        if name == "christofides":
            return C.christofides(codes)
        if name == "optimal":
            return I.optimal(codes)
        if name in ("adjacent_swap", "window_swap", "reinsertion", "peephole"):
            return getattr(I, name)(codes, **opt)
        if name == "interleave":
            packed = np.sort(codes.astype("int64") * codes.shape[1] + np.arange(codes.shape[1]), axis=1)
            packed[:, 1::2] *= -1
            return np.lexsort(packed.T[::-1])
        if name == "lexicographic":
            return np.lexsort(codes.T[::-1])
        raise ValueError(f"unknown block method {name}")

    def together(blocks: list[np.ndarray], seeds: list[int]) -> list[np.ndarray]:
        orders, starts = L.list_orders(blocks[0].shape[1], k, lists), [_start(b, start, s, None) for b, s in zip(blocks, seeds, strict=True)]
        return L.walk_together(blocks, orders, starts, reuse_sort, gray)

    # only list walks have a way to do several blocks at once
    run.together = together if name == "multiple_lists" else None
    return run


def _solve(codes: np.ndarray, options: list[Callable], restarts: int, guard: bool, seed: int, before: np.ndarray | None) -> np.ndarray:
    """The best of all options and restarts; with `guard`, the given order unless one has fewer runs."""

    def cost(order: np.ndarray) -> int:
        path = codes[order]
        edge = 0 if before is None or not len(path) else int((path[0] != before).sum())
        return D.path_cost(path) + edge

    best = np.arange(len(codes)) if guard else None
    least = cost(best) if guard else None
    for option in options:
        for r in range(restarts):
            order = option(codes, seed + 7919 * r, before)
            if len(options) * restarts == 1 and not guard:
                return order
            c = cost(order)
            if least is None or c < least:
                best, least = order, c
    return best


def _codes(table: pa.Table | pa.RecordBatch, names: list[str]) -> np.ndarray:
    if not table.num_rows:
        return np.zeros((0, len(names)), "int64")
    return np.stack([np.asarray(table.column(n).to_numpy(zero_copy_only=False) if isinstance(table, pa.RecordBatch) else table.column(n).to_numpy(), dtype="int64") for n in names], axis=1)


def run_blocks(
    df: DataFrame, methods: list[Callable], code_cols: list[str], block_rows: int, shift: int = 0, restarts: int = 1,
    revert_if_worse: bool = False, seed: int = 0, by: list[str] | None = None, max_blocks: int | None = None, abreast: int = 1,
) -> DataFrame:
    """Applies the kernels to every block of a positioned frame; positions stay within their block.

    Blocks are keyed by id and dealt by hash, one task's memory holds one block; the result does
    not depend on the number of tasks. Blocks from number `max_blocks` on pass through unchanged.
    With `abreast`, one task's memory holds so many blocks, if the kernel can do several at once: same result."""
    blocked = assign_blocks(df, block_rows, by, shift)
    if abreast > 1 and len(methods) == restarts == 1 and not revert_if_worse and max_blocks is None and getattr(methods[0], "together", None):
        return _run_together(blocked, methods[0], code_cols, seed, abreast)

    def work(table: pa.Table) -> pa.Table:
        table = table.sort_by("pos")
        block = table.column("block_id")[0].as_py()
        if max_blocks is not None and block >= max_blocks:
            return table
        codes = _codes(table, code_cols)
        order = _solve(codes, methods, restarts, revert_if_worse, abs(hash((seed, block))) % (1 << 31), None)
        moved = table.take(pa.array(order))
        return moved.set_column(moved.schema.get_field_index("pos"), table.schema.field("pos"), table.column("pos"))

    return blocked.groupBy("block_id").applyInArrow(work, blocked.schema).drop("block_id")


def _run_together(blocked: DataFrame, method: Callable, code_cols: list[str], seed: int, abreast: int) -> DataFrame:
    """Groups of `abreast` blocks, the blocks of each done at once by `method`."""

    def work(table: pa.Table) -> pa.Table:
        pos, ids = table.column("pos").to_numpy(), table.column("block_id").to_numpy()
        turn = np.lexsort((pos, ids))
        ids = ids[turn]
        edges = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
        columns = [table.column(n).to_numpy() for n in code_cols]
        narrow = all(x.max(initial=0) < 1 << 31 for x in columns)
        blocks = []
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            block = np.empty((b - a, len(columns)), "int32" if narrow else "int64")
            for j, x in enumerate(columns):
                block[:, j] = x[turn[a:b]]
            blocks.append(block)
        seeds = [abs(hash((seed, int(ids[a])))) % (1 << 31) for a in edges[:-1]]
        orders = method.together(blocks, seeds)
        moved = table.take(pa.array(np.concatenate([turn[a + order] for a, order in zip(edges[:-1], orders, strict=True)])))
        return moved.set_column(moved.schema.get_field_index("pos"), table.schema.field("pos"), pa.array(pos[turn], table.schema.field("pos").type))

    grouped = blocked.withColumn("__group", F.floor(F.col("block_id") / abreast))
    return grouped.groupBy("__group").applyInArrow(work, grouped.schema).drop("__group", "block_id")


#: Codes of the blocks that a task holds at once.
ABREAST_CODES = 3 << 22


def blocks_abreast(spark: SparkSession, rows: int, columns: int, block_rows: int) -> int:
    """How many blocks to do at once: as many as a task may hold, but no fewer groups than cores."""
    blocks = -(-rows // block_rows)
    return max(1, min(ABREAST_CODES // (block_rows * columns), -(-blocks // spark.sparkContext.defaultParallelism)))


def run_blocks_local(
    df: DataFrame, methods: list[Callable], code_cols: list[str], block_rows: int, chain: bool = False,
    restarts: int = 1, revert_if_worse: bool = False, seed: int = 0,
) -> DataFrame:
    """Cuts each sorted partition in blocks where it stands, without another shuffle.

    With `chain`, a block starts near the last row of the block before it. Rows come out in their
    new order, to be numbered by `numbered`; a retried task gives the same rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size, index = 0, 0
        last: np.ndarray | None = None

        def solve(table: pa.Table) -> pa.Table:
            nonlocal last, index
            codes = _codes(table, code_cols)
            order = _solve(codes, methods, restarts, revert_if_worse, seed + index, last if chain else None)
            last, index = codes[order[-1]], index + 1
            return table.take(pa.array(order))

        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            while size >= block_rows:
                table = pa.Table.from_batches(held)
                yield from solve(table.slice(0, block_rows)).to_batches()
                rest = table.slice(block_rows)
                held, size = rest.to_batches(), rest.num_rows
        if size:
            yield from solve(pa.Table.from_batches(held)).to_batches()

    return df.mapInArrow(run, df.schema)


def _coded(df: DataFrame, cols: list[str]) -> tuple[DataFrame, list[str]]:
    """Codes of positioned rows, as columns beside them."""
    dictionary = build_dictionary(df.drop("pos"), cols)
    return encode(df, dictionary, cols), [c + "__code" for c in cols]


def reorder_blocks(
    df: DataFrame, methods: str | list[str] = "multiple_lists", cols: list[str] | None = None, block_rows: int = TOUR_ROWS,
    base: str | None = "lexicographic", column_order_mode: str | list[str] = "asc_card", tie: list[str] | None = None,
    restarts: int = 1, revert_if_worse: bool = False, rounds: int = 1, seed: int = 0, by: list[str] | None = None,
    max_blocks: int | None = None, keep_codes: bool = False, **opt,  # noqa: ANN003
) -> DataFrame:
    """`df` with `pos`: a base order (or the given `pos`, with base None), then block methods.

    Every second round cuts the blocks half a block further, so that rows cross borders."""
    if base is None:
        cols = cols or [c for c in df.columns if c != "pos"]
        cols = column_order(df, cols, column_order_mode)
        coded, codes = _coded(df, cols)
    else:
        cols = column_order(df, cols or [c for c in df.columns if c != "pos"], column_order_mode)
        coded = order_by(df, base, cols, "given", keep_codes=True, tie=tie)
        codes = [c + "__code" for c in cols]
    names = [methods] if isinstance(methods, str) else methods
    solvers = [kernel(m, **opt) for m in names]
    for r in range(rounds):
        shift = block_rows // 2 if r % 2 else 0
        coded = run_blocks(coded, solvers, codes, block_rows, shift, restarts, revert_if_worse, seed + r, by, max_blocks)
    return coded if keep_codes else coded.drop(*codes)


def tour(df: DataFrame, heuristic: str, cols: list[str] | None = None, block_rows: int = TOUR_ROWS, start: str | int = "first", seed: int = 0, distance: str = "hamming", **opt) -> DataFrame:  # noqa: ANN003
    """A tour-construction heuristic in every block of the lexicographic order."""
    if distance != "hamming":
        opt["kind"] = distance
    engine = {k: opt.pop(k) for k in ("base", "column_order_mode", "tie", "restarts", "revert_if_worse", "rounds", "keep_codes") if k in opt}
    return reorder_blocks(df, heuristic, cols, block_rows, seed=seed, start=start, **engine, **opt)


def improve(df: DataFrame, method: str, cols: list[str], block_rows: int = TOUR_ROWS, rounds: int = 1, **opt) -> DataFrame:  # noqa: ANN003
    """A tour improvement in every block of an existing order; a block never gets worse."""
    return reorder_blocks(df, method, cols, block_rows, base=None, column_order_mode="given", revert_if_worse=True, rounds=rounds, **opt)


def multiple_lists(df: DataFrame, cols: list[str] | None = None, k: int | None = None, lists: str | list[list[int]] = "rotations", start: str | int = "first", seed: int = 0, **opt) -> DataFrame:  # noqa: ANN003
    """One walk over the whole table as a single block. Tables of more than WHOLE_ROWS rows are refused:
    one task would hold them; `multiple_lists_blocked` takes any size."""
    n = df.count()
    if n > WHOLE_ROWS:
        raise ValueError(f"{n} rows are too many for one walk; use multiple_lists_blocked")
    return reorder_blocks(df, "multiple_lists", cols, 1 << 62, start=start, seed=seed, k=k, lists=lists, **opt)


def multiple_lists_blocked(
    df: DataFrame, cols: list[str] | None = None, block_rows: int = BLOCK_ROWS, blocking: str = "global",
    revert_if_worse: bool = False, start: str | int = "first", keep_codes: bool = False, tie: list[str] | None = None, **opt,  # noqa: ANN003
) -> DataFrame:
    """The lexicographic order cut in blocks, with a list walk in each.

    global: blocks of the global position, the same at any parallelism. local: blocks of each
    sorted partition, with no shuffle after the sort and a start near the block before."""
    if blocking == "global":
        return reorder_blocks(df, "multiple_lists", cols, block_rows, revert_if_worse=revert_if_worse, start=start, keep_codes=keep_codes, tie=tie, **opt)
    cols = column_order(df, cols or [c for c in df.columns if c != "pos"], "asc_card")
    dictionary = build_dictionary(df, cols)
    codes = [c + "__code" for c in cols]
    coded = encode(df.drop("pos"), dictionary, cols)
    keys = [F.asc(c) for c in codes]
    placed = coded.repartitionByRange(*keys).sortWithinPartitions(*keys)
    walked = run_blocks_local(placed, [kernel("multiple_lists", start="nearest_to_prev", **opt)], codes, block_rows, chain=True, revert_if_worse=revert_if_worse)
    out = numbered(walked)
    return out if keep_codes else out.drop(*codes)


def block_log(before: DataFrame, after: DataFrame, codes: list[str], block_rows: int) -> DataFrame:
    """(block_id, rows, runs_before, runs_after, kept) of every block, runs counted inside blocks."""

    def runs_of(df: DataFrame, name: str) -> DataFrame:
        def count(table: pa.Table) -> pa.Table:
            table = table.sort_by("pos")
            c = _codes(table, codes)
            return pa.table({"block_id": [table.column("block_id")[0].as_py()], "rows": pa.array([len(c)], pa.int32()), name: [D.runs(c)]})

        schema = T.StructType([T.StructField("block_id", T.LongType()), T.StructField("rows", T.IntegerType()), T.StructField(name, T.LongType())])
        return assign_blocks(df.select("pos", *codes), block_rows).groupBy("block_id").applyInArrow(count, schema)

    return runs_of(before, "runs_before").join(runs_of(after, "runs_after").drop("rows"), "block_id").withColumn("kept", F.col("runs_after") < F.col("runs_before"))


def early_stop(df: DataFrame, cols: list[str], blocks: int = 20, block_rows: int = BLOCK_ROWS, min_gain: float = 1.0, budget_s: float | None = None, **opt) -> tuple[DataFrame, float, bool]:  # noqa: ANN003
    """Walks the first `blocks` blocks; goes on with all of them only if they gain enough in time.

    Returns the reordered frame, the gain of the pilot (runs before over runs after) and whether
    it went on. Gains made before stopping stay."""
    began = time.time()
    coded = order_by(df, "lexicographic", cols, keep_codes=True)
    names = [c for c in coded.columns if c.endswith("__code")]
    first = coded.where(F.col("pos") < blocks * block_rows)
    piloted = run_blocks(first, [kernel("multiple_lists", **opt)], names, block_rows)
    log = block_log(first, piloted, names, block_rows).agg(F.sum("runs_before"), F.sum("runs_after")).first()
    gain = (log[0] or 1) / (log[1] or 1)
    go = gain > min_gain and (budget_s is None or time.time() - began < budget_s)
    done = run_blocks(coded, [kernel("multiple_lists", **opt)], names, block_rows, max_blocks=None if go else blocks)
    return done.drop(*names), gain, go
