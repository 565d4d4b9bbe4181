"""Column chunks as bytes: encoding a reordered table, decoding it, and its real size."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.operators.kernels import codecs
from rowloom.operators.runs import few_rows
from rowloom.operators.sizes import long_codes
from rowloom.operators.survey import CHUNK, survey


def encode_chunks(df: DataFrame, cols: list[str], kind: str, cards: list[int], chunk: int = CHUNK) -> DataFrame:
    """(i, chunk, rows, data): every `chunk` positions of each code column as one encoded value."""
    long = long_codes(df, cols).withColumn("chunk", F.floor(F.col("pos") / chunk))
    sizes = list(cards)

    def work(table: pa.Table) -> pa.Table:
        table = table.sort_by("pos")
        i = table.column("i")[0].as_py()
        data = codecs.encode(table.column("code").to_numpy(), kind, sizes[i])
        return pa.table({"i": pa.array([i], pa.int32()), "chunk": [table.column("chunk")[0].as_py()], "rows": [table.num_rows], "data": pa.array([data], pa.binary())})

    return long.groupBy("i", "chunk").applyInArrow(work, "i int, chunk long, rows long, data binary")


def decode_chunks(chunks: DataFrame, kind: str, chunk: int = CHUNK) -> DataFrame:
    """(i, pos, code) of encoded chunks."""

    def run(batches):  # noqa: ANN001, ANN202
        for batch in batches:
            for i, k, data in zip(*(batch.column(c).to_pylist() for c in ("i", "chunk", "data")), strict=True):
                codes = codecs.decode(data, kind)
                n = len(codes)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([i] * n, pa.int32()), pa.array(range(k * chunk, k * chunk + n), pa.int64()), pa.array(codes)], names=["i", "pos", "code"]
                )

    return chunks.mapInArrow(run, "i int, pos long, code long")


def encoded_bits(
    df: DataFrame, cols: list[str], kind: str, cards: list[int], method: str = "given", chunk: int = CHUNK, facts: dict[str, list[int]] | None = None,
) -> DataFrame:
    """(method, codec, col, bits) of the encoded bytes, for codecs without a size formula.

    Chunks are encoded where their rows are. `facts` are a `survey` of the same rows with this codec."""
    found = facts if facts and kind in facts else survey(df, cols, cards, [kind], chunk=chunk)
    names = F.element_at(F.array(*[F.lit(c) for c in cols]), F.col("i") + 1)
    return few_rows(df.sparkSession, found[kind], "bits").select(F.lit(method).alias("method"), F.lit(kind).alias("codec"), names.alias("col"), "bits")
