"""One reading of a frame for all measures, and walks of several blocks at once, against the single ways."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from rowloom.operators import blocks as B
from rowloom.operators import runs as R
from rowloom.operators import sizes as Z
from rowloom.operators.encoded import encode_chunks, encoded_bits
from rowloom.operators.kernels import lists as L
from rowloom.operators.survey import survey

COLS, CARDS = ["a", "b", "c"], [3, 40, 1]
KINDS = [*Z.BLOCK_CODECS, "runcount", "lz4_raw"]


def frame(spark, n, gaps=False):
    df = spark.range(n).select(F.col("id").alias("pos"), (F.col("id") / 7 % 3).cast("long").alias("a"), (F.hash("id") % 20 + 20).cast("long").alias("b"), F.lit(0).cast("long").alias("c"))
    return df.where("pos % 1000 <> 7 and not (pos between 300 and 700)") if gaps else df


def bits(df, name="bits"):
    return {r["col"]: r[name] for r in df.collect()}


@pytest.mark.parametrize(("n", "tasks", "gaps"), [(2000, 1, False), (2000, 7, False), (2000, 7, True), (50, 3, False), (0, 1, False)])
@pytest.mark.parametrize("dealt", [False, True])
def test_survey_is_what_each_operator_sums(spark, n, tasks, gaps, dealt):
    df = frame(spark, n, gaps)
    df = df.repartition(tasks, "b") if dealt else df.repartitionByRange(tasks, "pos").sortWithinPartitions("pos")
    facts = survey(df, COLS, CARDS, KINDS, chunk=512)
    assert facts["rows"] == [df.count()]
    for codec in (*Z.BLOCK_CODECS, "rle", "dictionary"):
        assert bits(Z.size(df, codec, COLS, cards=CARDS, facts=facts)) == bits(Z.size(df, codec, COLS, cards=CARDS))
    assert bits(R.run_count(df, COLS, facts=facts), "runs") == bits(R.run_count(df, COLS), "runs")
    chunks = {i: 0 for i in range(3)} | {r["i"]: r["n"] for r in encode_chunks(df, COLS, "lz4_raw", CARDS, 512).groupBy("i").agg(F.sum(F.length("data") * 8).alias("n")).collect()}
    assert bits(encoded_bits(df, COLS, "lz4_raw", CARDS, facts=facts)) == {c: chunks[i] for i, c in enumerate(COLS)}


@pytest.mark.parametrize("c", [1, 3, 7, 8, 15, 42])
def test_walks_together_are_the_walks(c):
    rng = np.random.default_rng(c)
    blocks = [np.minimum(rng.geometric(0.2, (n, c)), 9).astype("int64") for n in (60, 1, 0, 200, 60, 2)]
    for gray in (False, True):
        got = L.walk_together(blocks, gray=gray)
        assert [g.tolist() for g in got] == [L.walk(b, gray=gray).tolist() for b in blocks]
    starts = [5, 0, 0, 199, 0, 1]
    huge = [b + (1 << 40) for b in blocks]
    assert [g.tolist() for g in L.walk_together(huge, starts=starts)] == [L.walk(b, start=s).tolist() for b, s in zip(huge, starts, strict=True)]


@pytest.mark.parametrize("start", ["first", "random"])
def test_blocks_abreast_give_the_same_rows(spark, start):
    df = frame(spark, 3000)
    kernel = B.kernel("multiple_lists", start=start)
    one = B.run_blocks(df, [kernel], COLS, 256, seed=3)
    many = B.run_blocks(df, [kernel], COLS, 256, seed=3, abreast=5)
    assert many.columns == one.columns
    assert sorted(map(tuple, many.collect())) == sorted(map(tuple, one.collect()))
