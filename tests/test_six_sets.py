"""The stand-in sets, their codes and their orders against SQL and the general way."""

from __future__ import annotations

import compare
import pytest

from rowloom.operators import order as O
from rowloom.operators import runs as R
from rowloom.operators.dictionary import build_dictionary
from rowloom.plans import oracle as S
from rowloom.plans.workloads import WORKS
from rowloom.sources.scratch import passing, scratch_path, written

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("work", ["wide", "duplicates", "weather"])
def test_made_rows_are_those_of_sql(spark, work):
    mine, theirs = compare.both(WORKS[work].frame(spark, SF), compare.connect(SF), WORKS[work].sql)
    assert mine == theirs
    assert "MapInArrow" in WORKS[work].frame(spark, SF)._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("order", ["lexicographic", "interleave", "frequent_component"])
def test_codes_alone_take_the_same_order(spark, order):
    w = WORKS["orders"]
    df = w.frame(spark, SF)
    coded = O.code_table(df, w.cols, build_dictionary(df, w.cols), freq=True)
    codes = [c + "__code" for c in w.cols]
    placed = O.order_codes(coded, order, codes, [c + "__freq" for c in w.cols])
    assert placed.columns == [*codes, "pos"]
    sql = S.run_rows(w.sql, w.cols, "codes" if order == "lexicographic" else order, order)
    mine = sorted((r["col"].removesuffix("__code"), r["runs"]) for r in R.run_count(placed, codes, order).collect())
    theirs = sorted((c, n) for _, c, n in compare.connect(SF).execute(sql).fetchall())
    assert mine == theirs


def test_passing_tables_go_with_their_block(spark):
    kept = written(spark.range(3))
    with passing(spark):
        with passing(spark):
            path = scratch_path(spark, "x")
            spark.range(2).write.parquet(path)
        with pytest.raises(Exception):
            spark.read.parquet(path).count()
    assert kept.count() == 3


@pytest.mark.parametrize("name", ["ssb_like_run_count", "ssb_growth"])
def test_tables_on_the_way_do_not_stay(spark, name):
    import os

    import __spark_entry__ as entry

    top = os.path.dirname(scratch_path(spark, "x")).removeprefix("file:")
    before = set(os.listdir(top)) if os.path.isdir(top) else set()
    mine, theirs = compare.both(entry.queries()[name](spark, SF), compare.connect(SF), entry.oracle_sql()[name])
    assert mine == theirs
    assert set(os.listdir(top)) <= before
