"""Everything that is summed over a reordered code table, from one reading of it.

A task holds the rows of every chunk of positions until it has them all, and measures the chunk
where it is; only chunks that tasks share leave them, as bytes. What comes out is a row for each
chunk, and in the end a few numbers on the driver."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.functions.bits import bits_of
from rowloom.operators.kernels import codecs
from rowloom.operators.sizes import BLOCK, BLOCK_CODECS, block_costs

CHUNK = 65_536
#: Rows of chunks that are still open, over which a task lets them go as pieces.
OPEN_ROWS = 4 * CHUNK

_CHUNK = "chunk long, rows long, first long, last long, heads array<long>, tails array<long>, found array<long>, pos binary, codes binary"


def _cost(codes: np.ndarray, ids: np.ndarray, kind: str, width: int, p: int) -> int:
    """Bits of one column under a block codec; `ids` are the coding blocks of its rows, in order."""
    edges = np.concatenate([[0], np.flatnonzero(ids[1:] != ids[:-1]) + 1, [len(ids)]])
    lengths, total = np.diff(edges), 0
    for n in np.unique(lengths):
        rows = edges[:-1][lengths == n][:, None] + np.arange(n)
        total += int(block_costs(codes[rows], kind, width, p).sum())
    return total


def _measure(pos: np.ndarray, codes: np.ndarray, kinds: list[str], cards: list[int], p: int) -> list[int]:
    """For each of `kinds`, a number for each row of `codes` (a column of the table): bits, or runs that start inside the chunk."""
    ids, found = pos // p, []
    gaps = pos[1:] != pos[:-1] + 1
    for kind in kinds:
        if kind == "runcount":
            found += ((codes[:, 1:] != codes[:, :-1]) | gaps).sum(axis=1).tolist()
        elif kind in BLOCK_CODECS:
            found += [_cost(c, ids, kind, bits_of(n), p) for c, n in zip(codes, cards, strict=True)]
        else:
            found += [8 * len(codecs.encode(c, kind, n)) for c, n in zip(codes, cards, strict=True)]
    return found


def _row(chunk: int, pos: np.ndarray, codes: np.ndarray, found: list[int] | None) -> dict:
    whole = found is not None
    return {
        "chunk": chunk, "rows": len(pos), "first": int(pos[0]), "last": int(pos[-1]),
        "heads": codes[:, 0].tolist() if whole else None, "tails": codes[:, -1].tolist() if whole else None, "found": found,
        "pos": None if whole else pos.tobytes(), "codes": None if whole else np.ascontiguousarray(codes).tobytes(),
    }


_ARROW = pa.schema([
    ("chunk", pa.int64()), ("rows", pa.int64()), ("first", pa.int64()), ("last", pa.int64()), ("heads", pa.list_(pa.int64())),
    ("tails", pa.list_(pa.int64())), ("found", pa.list_(pa.int64())), ("pos", pa.binary()), ("codes", pa.binary()),
])


def survey(df: DataFrame, cols: list[str], cards: list[int], kinds: list[str], p: int = BLOCK, chunk: int = CHUNK) -> dict[str, list[int]]:
    """For each of `kinds` (block codecs, byte codecs, `runcount`) a number for each column: bits or runs.
    `rows` has the one number of rows. `df` has distinct `pos`, and codes that are not null."""
    if chunk % p and set(kinds) & set(BLOCK_CODECS):
        raise ValueError("a chunk holds whole coding blocks")
    kinds, cards, c = list(kinds), list(cards), len(cols)

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        sizes: dict[int, int] = {}

        def joined(k: int) -> tuple[np.ndarray, np.ndarray]:
            parts = held.pop(k)
            del sizes[k]
            pos, codes = np.concatenate([x for x, _ in parts]), np.concatenate([y for _, y in parts], axis=1)
            if (pos[1:] < pos[:-1]).any():
                turn = np.argsort(pos)
                pos, codes = pos[turn], codes[:, turn]
            return pos, codes

        def pieces() -> Iterator[pa.RecordBatch]:
            for k in list(held):
                yield pa.RecordBatch.from_pylist([_row(k, *joined(k), None)], _ARROW)

        for batch in batches:
            if not batch.num_rows:
                continue
            pos = batch.column(0).to_numpy().astype("int64")
            codes = np.stack([x.to_numpy(zero_copy_only=False) for x in batch.columns[1:]]).astype("int64", copy=False)
            own = pos // chunk
            for k in np.unique(own).tolist():
                at = np.flatnonzero(own == k)
                at = slice(at[0], at[-1] + 1) if at[-1] - at[0] + 1 == len(at) else at
                held.setdefault(k, []).append((pos[at], codes[:, at]))
                sizes[k] = sizes.get(k, 0) + len(pos[at])
                if sizes[k] == chunk:
                    x, y = joined(k)
                    yield pa.RecordBatch.from_pylist([_row(k, x, y, _measure(x, y, kinds, cards, p))], _ARROW)
            if sum(sizes.values()) > OPEN_ROWS:
                yield from pieces()
        yield from pieces()

    def whole(table: pa.Table) -> pa.Table:
        if table.column("found").null_count == 0:
            return table
        pos = np.concatenate([np.frombuffer(x, "int64") for x in table.column("pos").to_pylist()])
        codes = np.concatenate([np.frombuffer(x, "int64").reshape(c, -1) for x in table.column("codes").to_pylist()], axis=1)
        turn = np.argsort(pos)
        pos, codes = pos[turn], codes[:, turn]
        return pa.Table.from_pylist([_row(table.column("chunk")[0].as_py(), pos, codes, _measure(pos, codes, kinds, cards, p))], _ARROW)

    own = df.select("pos", *[F.col(f"`{x}`").cast("long").alias(f"c{j}") for j, x in enumerate(cols)])
    chunks = own.mapInArrow(local, _CHUNK).groupBy("chunk").applyInArrow(whole, _CHUNK).select("rows", "first", "last", "heads", "tails", "found")
    # a chunk's first row meets the last row of the chunk before it at its position
    head = F.struct(F.col("first").alias("at"), "rows", "heads", F.lit(None).cast("array<long>").alias("tails"), "found")
    tail = F.struct((F.col("last") + 1).alias("at"), F.lit(None).cast("long").alias("rows"), F.lit(None).cast("array<long>").alias("heads"), "tails", F.lit(None).cast("array<long>").alias("found"))
    ends = chunks.select(F.explode(F.array(head, tail)).alias("e")).select("e.*")
    firsts = [F.first(x, ignorenulls=True).alias(x) for x in ("rows", "heads", "tails", "found")]
    met = ends.groupBy("at").agg(*firsts).where("rows is not null")
    starts = [F.sum((F.col("tails").isNull() | (F.get("heads", F.lit(j)) != F.get("tails", F.lit(j)))).cast("long")).alias(f"s{j}") for j in range(c)]
    sums = [F.sum(F.get("found", F.lit(j))).alias(f"f{j}") for j in range(c * len(kinds))]
    row = met.agg(F.sum("rows").alias("rows"), *starts, *sums).first()
    facts = {kind: [row[f"f{i * c + j}"] or 0 for j in range(c)] for i, kind in enumerate(kinds)}
    if "runcount" in facts:
        facts["runcount"] = [x + (row[f"s{j}"] or 0) for j, x in enumerate(facts["runcount"])]
    return facts | {"rows": [row["rows"] or 0]}
