"""The flagship result: how much smaller each codec makes a table in the orders worth trying."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowloom.operators import blocks as B
from rowloom.operators import order as O
from rowloom.operators import runs as R
from rowloom.operators import sizes as Z
from rowloom.operators.dictionary import build_dictionary, cardinalities, settled
from rowloom.operators.encoded import encoded_bits
from rowloom.operators.survey import survey
from rowloom.plans.workloads import WORKS
from rowloom.sources.scratch import written

CODECS = ("dictionary", "sparse", "indirect", "prefix", "rle")


def comparison(spark: SparkSession, sf_dir: str, work: str = "lineitem", block_rows: int = B.BLOCK_ROWS, lz: str | None = None) -> DataFrame:
    """(method, codec, bits, ratio): sizes under each order, and the sorted order's over them. RunCount is in runs.

    `lz` names a codec of the LZ class whose bytes are measured too."""
    w = WORKS[work]
    df = settled(w.frame(spark, sf_dir))
    dictionary = build_dictionary(df, w.cols)
    cards = cardinalities(dictionary, w.cols)
    codes = [c + "__code" for c in w.cols]
    coded = O.code_table(df, w.cols, dictionary)
    frames = {
        "lexicographic": O.order_codes(coded, "lexicographic", codes),
        "interleave": O.order_codes(coded, "interleave", codes),
    }
    abreast = B.blocks_abreast(spark, coded.count(), len(codes), block_rows)
    frames["multiple_lists_blocked"] = written(B.run_blocks(frames["lexicographic"], [B.kernel("multiple_lists")], codes, block_rows, abreast=abreast), "walked")
    rows = None
    for method, frame in frames.items():
        # a frame is read once for all that is summed over it
        facts = survey(frame, codes, cards, [*Z.BLOCK_CODECS, "runcount", *([lz] if lz else [])])
        parts = [Z.size(frame, codec, codes, method, cards, facts=facts) for codec in CODECS]
        runs = R.run_count(frame, codes, method, facts=facts).select("method", F.lit("runcount").alias("codec"), "col", F.col("runs").alias("bits"))
        parts += [encoded_bits(frame, codes, lz, cards, method, facts=facts)] if lz else []
        for one in [*parts, runs]:
            rows = one if rows is None else rows.unionByName(one)
    total = rows.groupBy("method", "codec").agg(F.sum("bits").alias("bits"))
    base = total.where("method = 'lexicographic'").select("codec", F.col("bits").alias("base"))
    return total.join(base, "codec").select("method", "codec", "bits", F.round(F.col("base") / F.col("bits"), 6).alias("ratio"))
