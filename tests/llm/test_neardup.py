from __future__ import annotations

import numpy as np
import pytest

from rowloom.llm import neardup, setjoin
from rowloom.llm.components import connected_components


def brute(rows, width=5, threshold=85):
    sets = {}
    for d, t in rows:
        w = (t or "").encode().lower().split()
        s = {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
        sets.setdefault(d, []).append(s)
    ids = [d for d in sets if d is not None]
    lead = {d: d for d in ids}

    def find(x):
        while lead[x] != x:
            x = lead[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if any(x and y and 100 * len(x & y) >= threshold * len(x | y) for x in sets[a] for y in sets[b]):
                x, y = find(a), find(b)
                lead[max(x, y)] = min(x, y)
    return {d: find(d) for d in ids}, {d: sorted(map(len, s)) for d, s in sets.items()}


def same(frame, rows):
    want, sizes = brute(rows)
    got = neardup.near_duplicates(frame).collect()
    assert len(got) == len(rows)
    for r in got:
        if r["doc_id"] is None:
            assert r["component_id"] is None and r["kept"]
            continue
        assert r["component_id"] == want[r["doc_id"]], r
        assert r["kept"] == (r["doc_id"] == r["component_id"])
        assert r["n_shingles"] in sizes[r["doc_id"]]


def test_given_documents(documents):
    same(documents, [(r["doc_id"], r["text"]) for r in documents.collect()])


def test_odd_rows(odd_docs, no_docs):
    same(odd_docs, [(r["doc_id"], r["text"]) for r in odd_docs.collect()])
    assert neardup.near_duplicates(no_docs).count() == 0


def test_a_dense_group_around_one_text(spark):
    """Hundreds of edits of one text, of which few are near each other: all meet through it."""
    rng = np.random.default_rng(2)
    base = [f"w{i}" for i in range(150)]
    rows = [(1000, " ".join(base))]
    for k in range(260):
        own = list(base)
        for at in rng.choice(150, 1 + int(rng.integers(0, 3)), replace=False):
            own[at] = f"e{k}x{at}"
        rows.append((k, " ".join(own)))
    rows += [(2000 + k, " ".join(f"z{k}q{i}" for i in range(40))) for k in range(30)]
    same(spark.createDataFrame(rows, "doc_id long, text string"), rows)


def test_a_templated_crowd(spark):
    """14,641 fillings of one template, no two of them near, and 400 that link some: any two within
    one field (111 of 121 shingles) are near, those two fields apart (106 of 126) are not."""
    rng = np.random.default_rng(8)
    free = np.array(np.unravel_index(np.arange(11**4), (11,) * 4)).T
    codes = np.column_stack([free, -free.sum(axis=1) % 11])
    extra = codes[rng.choice(len(codes), 400, replace=False)].copy()
    for row, at in zip(extra, rng.integers(0, 5, len(extra)), strict=True):
        row[at] = (row[at] + rng.integers(1, 11)) % 11
    codes = rng.permutation(np.unique(np.concatenate([codes, extra]), axis=0))

    def text(code):
        words = [f"b{i}" for i in range(120)]
        for f, v in enumerate(code):
            words[10 + 24 * f] = f"f{f}v{v}"
        return " ".join(words)

    lead = list(range(len(codes)))

    def find(x):
        while lead[x] != x:
            x = lead[x]
        return x

    for i in range(len(codes)):
        for j in i + 1 + np.flatnonzero((codes[i + 1 :] != codes[i]).sum(axis=1) <= 1):
            x, y = find(i), find(int(j))
            lead[max(x, y)] = min(x, y)
    want = {i: find(i) for i in range(len(codes))}
    assert len(set(want.values())) < len(codes) - 1000
    docs = spark.createDataFrame([(i, text(c)) for i, c in enumerate(codes.tolist())], "doc_id long, text string")
    assert {r["doc_id"]: r["component_id"] for r in neardup.near_duplicates(docs).collect()} == want


def test_set_join_in_chunks(spark, monkeypatch):
    """Blocks of few sets, several sets of one id, and a large component beside single sets."""
    rng = np.random.default_rng(9)
    monkeypatch.setattr(setjoin, "CHUNK_SETS", 7)
    rows = []
    for k in range(240):
        own = np.arange(60, dtype=np.uint64)
        own[rng.choice(60, int(rng.integers(1, 9)), replace=False)] += np.uint64(1000 * int(rng.integers(1, 6)))
        rows.append((k // 2 if k < 40 else k, 0 if 100 <= k < 170 else (k // 2 if k < 40 else k), np.sort(own)))
    want = set()
    for i, (_, a, x) in enumerate(rows):
        for _, b, y in rows[i + 1 :]:
            common = len(np.intersect1d(x, y))
            if a != b and 100 * common >= 85 * (len(x) + len(y) - common):
                want.add((min(a, b), max(a, b)))
    crowd = spark.createDataFrame(sorted({(d, c) for d, c, _ in rows}), "did long, component long")
    sets = spark.createDataFrame([(d, bytearray(s.tobytes())) for d, _, s in rows], "did long, members binary")
    got = {(r["a"], r["b"]) for r in setjoin.component_links(crowd, sets, 85).collect()}
    assert len(want) > 100 and got == want


def test_the_threshold_is_exact(spark):
    """20 shingles of 24 words: 100 * 17 / 20 = 85 links, 16 / 20 does not."""
    a = [f"a{i}" for i in range(24)]
    rows = [(1, " ".join(a)), (2, " ".join(a[:21])), (3, " ".join(a[:20])), (4, "one two three"), (5, "ONE two\tthree"), (6, "one two")]
    same(spark.createDataFrame(rows, "doc_id long, text string"), rows)


def test_orders_follow_the_threshold():
    assert neardup.forest(85) == (24, 5)
    for t in range(11, 101):
        trees, root = neardup.forest(t)
        assert trees * root <= neardup.HASHES and (1 - (t / 100) ** root) ** trees <= neardup.MISS
        assert neardup.sketch_bound(t) <= neardup.HASHES * (1 + t / 100) / 2
    for t in (0, 10, 101):
        with pytest.raises(ValueError):
            neardup.near_duplicates(None, threshold=t)


def test_frequent_keys_are_dealt(spark):
    """Half of the rows share a key: they are broadcast to, and the rest is dealt by key and salt together."""
    from rowloom.llm.shared import spread_join

    left = spark.range(6000).selectExpr("id", "if(id % 2 = 0, 1, id) as k")
    right = left.groupBy("k").count().selectExpr("k", "count as w", "k * 10 as v").where("k < 4000")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        got = spread_join(left, right, ["k"], "w", 6000, outer=True)
        text = got._jdf.queryExecution().executedPlan().toString()
        assert any("hashpartitioning" in x and "__salt" in x for x in text.splitlines())
        rows = got.collect()
        assert len(rows) == 6000 and all(r["v"] == (r["k"] * 10 if r["k"] < 4000 else None) for r in rows)
        assert spread_join(left, right, ["k"], "w", 6000).count() == sum(r["k"] < 4000 for r in rows)
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def _shuffled(spark):
    """Bytes that all stages of the session have written to shuffles."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))


def test_a_sieve_drops_only_rows_without_a_key(spark, monkeypatch):
    """Every row with a key is hit, few others are; with far more keys than bits all are hit."""
    from rowloom.llm import shared

    rows = spark.range(20_000).selectExpr("if(id % 100 = 99, null, id) as k", "id as v")
    keys = spark.range(0, 20_000, 7).selectExpr("id as k")
    for bits, most in ((20, 60), (1, 20_000)):
        monkeypatch.setattr(shared, "SIEVE_BITS", bits)
        got = shared.sieve(rows, keys, ["k"]).collect()
        assert len(got) == 20_000 and all(r["__hit"] for r in got if r["k"] is not None and r["k"] % 7 == 0)
        assert sum(r["__hit"] and (r["k"] is None or r["k"] % 7 > 0) for r in got) <= most
    assert shared.sieve(rows, keys.where("false"), ["k"]).where("__hit").count() == 0


def test_texts_without_a_near_one_are_not_shuffled(spark):
    """1,500 texts far from each other and 30 copies: only what may have a partner is dealt, however large the tables."""
    rng = np.random.default_rng(3)
    rows = [(i, " ".join(f"w{x}" for x in rng.integers(0, 10**9, 150))) for i in range(1500)]
    rows += [(2000 + i, rows[i][1] if i % 2 else rows[i][1] + " more") for i in range(30)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        before = _shuffled(spark)
        copies = neardup.near_duplicates(frame).where("not kept").select("doc_id").collect()
        moved = _shuffled(spark) - before
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert {r["doc_id"] for r in copies} == set(range(2000, 2030))
    assert moved < sum(len(t) for _, t in rows)


def test_components(spark):
    rng = np.random.default_rng(4)
    links = [(int(a), int(b)) for a, b in rng.integers(0, 300, (260, 2))] + [(1, 1), (None, 2)] + [(i, i + 1) for i in range(1000, 1100)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    lead: dict[int, int] = {}

    def find(x):
        while lead.setdefault(x, x) != x:
            x = lead[x]
        return x

    for a, b in links:
        if a is not None and a != b:
            x, y = find(a), find(b)
            lead[max(x, y)] = min(x, y)
    assert got == {x: find(x) for x in list(lead)}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0
