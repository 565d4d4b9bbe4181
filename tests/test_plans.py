"""Physical plans: no product joins, no ordering of all rows in one task, and filters in the scan."""

from __future__ import annotations

import contextlib
import io

from rowloom.operators import runs as R
from rowloom.operators import sizes as Z
from rowloom.operators.dictionary import histogram
from rowloom.operators.position import neighbours
from rowloom.plans import relational
from rowloom.sources.io import read_table

SF = "/root/testdata/sf0.001"


def plan(df) -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def clean(text: str) -> None:
    assert "CartesianProduct" not in text
    assert not ("Window" in text and "SinglePartition" in text and "Aggregate" not in text)
    assert "BatchEvalPython" not in text


def test_neighbours_window_by_block(spark):
    text = plan(neighbours(spark.range(100).selectExpr("id as pos", "id % 3 as v"), ["v"]))
    clean(text)
    assert "hashpartitioning(__block" in text and "SinglePartition" not in text


def exchanged(text: str) -> list[str]:
    """What each shuffle of a formatted plan moves."""
    return [line for block in text.split("\n\n") if ") Exchange" in block for line in block.splitlines() if line.startswith("Input")]


def test_run_count_does_not_shuffle_rows(spark):
    df = spark.range(100).selectExpr("id as pos", "id % 3 as v")
    text = plan(R.run_count(df, ["v"]))
    clean(text)
    assert "Window" not in text and "Sort [" not in text
    moved = exchanged(text)
    assert moved and all("c0#" not in x and "pos#" not in x and "v#" not in x for x in moved), moved
    assert text.count("MapInArrow") >= 1


def test_block_sizes_do_not_shuffle_rows(spark):
    df = spark.range(100).selectExpr("id as pos", "id % 3 as v")
    for codec in ("indirect", "sparse", "prefix"):
        text = plan(Z.size(df, codec, ["v"], cards=[3]))
        assert "Window" not in text and "CartesianProduct" not in text, codec
        moved = exchanged(text)
        assert moved and all("c0#" not in x and "pos#" not in x and "v#" not in x for x in moved), moved


def test_encode_broadcasts_frequent_values_only(spark, monkeypatch):
    """A short dictionary is broadcast; of a long one the most frequent values, and only the others are dealt."""
    from rowloom.operators import dictionary as D

    df = spark.range(2000).selectExpr("id % 3 as a", "if(id % 2 = 0, 7, id) as b")
    made = D.build_dictionary(df, ["a", "b"])
    monkeypatch.setattr(D, "HEAD", 100)
    text = plan(D.encode(df, made, ["a"]))
    assert "BroadcastHashJoin" in text and "SortMergeJoin" not in text and ") Exchange" not in text
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        coded = D.encode(df, made, ["a", "b"])
        text = plan(coded)
        assert text.count("SortMergeJoin LeftOuter") == 2 or text.count(") SortMergeJoin") == 1
        # rows are dealt by value and salt together
        assert any("hashpartitioning" in line and "__salt" in line for line in text.splitlines())
        want = {r["b"]: r["code"] for r in made.where("col_idx = 1").select("b", "code").collect()}
        rows = coded.collect()
        assert len(rows) == 2000 and all(r["b__code"] == want[r["b"]] for r in rows) and want[7] == 0
        back = D.decode(coded.drop("a", "b").selectExpr("*", "null as a", "null as b"), made, ["a", "b"])
        assert sorted((r["a"], r["b"]) for r in back.collect()) == sorted((r["a"], r["b"]) for r in df.collect())
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_histograms_scan_one_column_each(spark):
    text = plan(histogram(read_table(spark, SF, "lineitem"), ["l_returnflag", "l_linestatus"]))
    assert "ReadSchema: struct<l_returnflag:string>" in text and "ReadSchema: struct<l_linestatus:string>" in text
    assert "partial_count" in text


def test_filters_and_columns_reach_the_scan(spark):
    text = plan(relational.scan_parquet(spark, SF))
    assert "GreaterThan(l_quantity,25.0)" in text
    assert "ReadSchema: struct<l_linenumber:int,l_quantity:double,l_returnflag:string,l_linestatus:string>" in text
