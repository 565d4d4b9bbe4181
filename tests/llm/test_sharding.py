from __future__ import annotations

import zlib

import numpy as np
import pandas as pd

from rowloom.llm import sharding


def check(rows, docs, shards=8):
    assert len(rows) == len(docs)
    sizes = [0] * shards
    slots = [[] for _ in range(shards)]
    for r in rows:
        sizes[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots)
    largest = max((r["size"] for r in rows), default=0)
    assert all(abs(s - sum(sizes) / shards) < max(1, largest) for s in sizes)
    want = sorted((str(d), len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for d, t in docs)
    assert want == sorted((str(r["doc_id"]), r["size"], r["text_crc32"]) for r in rows)


def test_documents(documents):
    check(sharding.shard_documents(documents).collect(), [(r["doc_id"], r["text"]) for r in documents.collect()])


def test_odd_rows(odd_docs, no_docs):
    check(sharding.shard_documents(odd_docs).collect(), [(r["doc_id"], r["text"]) for r in odd_docs.collect()])
    assert sharding.shard_documents(no_docs).count() == 0


def test_one_key_with_a_third_of_the_rows(spark):
    docs = spark.range(900).selectExpr("if(id % 3 = 0, 77, id) as doc_id", "repeat('w', int(id % 50)) as text")
    check(sharding.shard_documents(docs).collect(), [(r["doc_id"], r["text"]) for r in docs.collect()])


def test_alike_rows_are_dealt(spark):
    """Half of the rows repeat one id and text: ties of every kind, over all shards."""
    docs = spark.range(4000).selectExpr("if(id % 2 = 0, 5, id) as doc_id", "if(id % 2 = 0, 'same', repeat('w', int(id % 50))) as text")
    rows = sharding.shard_documents(docs).collect()
    check(rows, [(r["doc_id"], r["text"]) for r in docs.collect()])
    nulls = spark.range(3000).selectExpr("cast(null as bigint) as doc_id", "cast(null as string) as text")
    check(sharding.shard_documents(nulls).collect(), [(None, None)] * 3000)


def test_sample_follows_sizes(spark):
    """Half of the bytes are in a hundredth of the rows: they give about half of the sample, under its bound or not."""
    rows = spark.range(50_000).selectExpr("id", "if(id < 500, 100, 1) as size")
    from pyspark.sql import functions as F

    for count in (1000, 20_000):
        got = sharding.weighted_sample(rows, "id", "size", F.xxhash64("id"), count, 50_000)
        assert len(got) == count and (np.diff(got) > 0).all()
    got = sharding.weighted_sample(rows, "id", "size", F.xxhash64("id"), 400, 50_000)
    assert 120 < (got < 500).sum() < 240


def test_whole_ranges_keep_their_shard():
    cells = pd.DataFrame({"range": [0, 1, 2, 3], "cell": [0] * 4, "bytes": [60, 30, 20, 90], "n": [6, 3, 2, 9]})
    got = sharding.whole_shards(sharding.subdivide(cells, 4), cells, 2)
    assert [g[-1] for g in got] == [0, 0, -1, 1]


def test_overfull_ranges_are_subdivided():
    cells = pd.DataFrame({"range": [0] * 8 + [1], "cell": [*range(8), 0], "bytes": [100] * 8 + [10], "n": [10] * 8 + [1]})
    blocks = sharding.subdivide(cells, 8)
    assert len({b for _, _, b, _, _ in blocks}) > 4
    assert blocks[-1][3:] == (800, 80)


def test_quantile_splitters():
    cuts = sharding.splitters(np.sort(np.arange(1000)), 4)
    assert cuts.tolist() == [250, 500, 750]
    assert len(sharding.splitters(np.zeros(50, "int64"), 8)) == 1
