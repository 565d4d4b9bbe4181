from __future__ import annotations

import zlib

import numpy as np
import pytest
from rowloom.llm import quality, toxicity

SF = "/root/testdata/sf0.01"


def accuracy(pairs):
    pairs = list(pairs)
    return sum(a == b for a, b in pairs) / len(pairs)


@pytest.fixture(scope="module")
def labelled(spark):
    return spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")


@pytest.mark.parametrize(("module", "label", "least"), [(toxicity, "toxic", 0.95), (quality, "quality", 0.95)])
def test_held_out_accuracy(labelled, module, label, least):
    docs, labels = labelled
    got = {r["doc_id"]: r for r in module.score(docs, module.train(docs, labels)).collect()}
    truth = {r["doc_id"]: r[label] for r in labels.collect()}
    assert all(r["held_out"] == (zlib.crc32(str(d).encode()) % 5 == 0) for d, r in got.items())
    assert accuracy([(got[d]["predicted"], y) for d, y in truth.items() if got[d]["held_out"]]) >= least
    assert all(0.0 <= r["score"] <= 1.0 for r in got.values())


@pytest.mark.parametrize("module", [toxicity, quality])
def test_held_out_labels_are_never_read(labelled, module):
    from pyspark.sql import functions as F

    docs, labels = labelled
    name = "toxic" if module is toxicity else "quality"
    flipped = labels.withColumn(name, F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, 1 - F.col(name)).otherwise(F.col(name)))
    a = {r["doc_id"]: r["score"] for r in module.score(docs, module.train(docs, labels)).collect()}
    b = {r["doc_id"]: r["score"] for r in module.score(docs, module.train(docs, flipped)).collect()}
    assert a == pytest.approx(b, abs=1e-9)


@pytest.mark.parametrize("module", [toxicity, quality])
def test_odd_rows_and_no_labels(spark, odd_docs, no_docs, module):
    labels = spark.createDataFrame([(1, 1, 0), (3, None, None), (None, 1, 1), (4, 0, 1), (4, 0, 1), (9, 0, 1)], "doc_id long, quality int, toxic int")
    for known in (labels, labels.where("false")):
        model = module.train(odd_docs, known)
        rows = module.score(odd_docs, model).collect()
        assert len(rows) == odd_docs.count() and all(r["score"] is not None and 0 <= r["score"] <= 1 for r in rows)
        assert module.keep(odd_docs, model).columns == odd_docs.columns
    assert module.score(no_docs, module.train(no_docs, labels.where("false"))).count() == 0


def test_interactions_are_learnt():
    """An insult is toxic only beside a group mention: no linear weights can tell."""
    rng = np.random.default_rng(0)
    rows, labels = [], []
    for _ in range(1600):
        a, b = rng.integers(0, 2, 2)
        noise = rng.integers(1000, 1200, 5)
        rows.append(np.unique(np.concatenate([[1] if a else [], [2] if b else [], noise])).astype("int32"))
        labels.append(float(a == b))
    labels = np.array(labels)
    assert {1, 2} <= set(toxicity.select_buckets(rows, labels).tolist())

    def right(model):
        place = {b: i for i, b in enumerate(model.buckets.tolist())}
        got = [model.score(np.array([place[x] for x in r.tolist() if x in place], "int64")) >= 0.5 for r in rows]
        return np.mean(np.array(got) == (labels > 0.5))

    assert right(toxicity.fit(rows, labels, epochs=60, rate=0.3, decay=0.0)) > 0.95
    assert right(toxicity.fit(rows, labels, epochs=60, rate=0.3, decay=0.0, rank=0)) < 0.7


def test_score_is_the_sum_over_all_pairs():
    rng = np.random.default_rng(3)
    model = toxicity.FactorizationMachine(np.arange(9, dtype="int32"), 0.3, rng.normal(0, 1, 9), rng.normal(0, 1, (9, toxicity.RANK)))
    for rows in ([], [4], [0, 2, 3, 8], list(range(9))):
        total = model.bias + sum(model.weights[i] for i in rows)
        total += sum(float(model.factors[i] @ model.factors[j]) for i in rows for j in rows if i < j)
        assert model.score(np.array(rows, "int64")) == pytest.approx(1 / (1 + np.exp(-total)), rel=1e-9)


def test_chosen_labels_are_the_smallest_hashes(spark):
    labels = spark.range(40_000).selectExpr("id as doc_id", "int(id % 2) as toxic")
    got = {r["label_id"] for r in toxicity.chosen_labels(labels, 500).collect()}
    own = labels.selectExpr("doc_id", "pmod(xxhash64(doc_id), 4503599627370496) as u", "crc32(cast(cast(doc_id as string) as binary)) % 5 as fold").where("fold <> 0")
    assert got == {r["doc_id"] for r in own.orderBy("u", "doc_id").limit(500).collect()}
    assert toxicity.chosen_labels(labels.where("doc_id < 100"), 500).count() == own.where("doc_id < 100").count()


def test_statistics_match_plain_counts():
    """Every statistic again, from its definition, on odd texts."""
    from collections import Counter

    def plain(text):
        words = text.split()
        lines = [x for x in text.split(b"\n") if x.strip()]
        n, m = len(text), len(words)
        share = lambda test: (sum(map(test, text)) / n) ** 0.5
        sizes = [len(w) for w in words]
        mean = sum(sizes) / m
        return {
            "log_bytes": np.log1p(n), "log_words": np.log1p(m), "word_length": np.log(mean),
            "word_spread": np.log1p((sum((x - mean) ** 2 for x in sizes) / m) ** 0.5), "longest_word": np.log(min(max(sizes), 1000)),
            "upper": share(lambda c: 65 <= c <= 90), "digit": share(lambda c: 48 <= c <= 57), "punct": share(lambda c: c in b".,;:?'\"-()"),
            "marks": share(lambda c: c in b"!#$%&*+/<=>@[\\]^_`{}~"), "bars": share(lambda c: c == 124), "lines": np.log1p(len(lines)),
            "line_length": np.log1p(n / len(lines)), "repeat_word": (1 - len(set(words)) / m) ** 0.5,
            "same_next": (sum(a == b for a, b in zip(words, words[1:], strict=False)) / m) ** 0.5,
            "repeat_line": (1 - len(set(lines)) / len(lines)) ** 0.5, "stops": (sum(w[-1:] in (b".", b"!", b"?") for w in words) / m) ** 0.5,
            "char_entropy": -sum(c / n * np.log2(c / n) for c in Counter(text).values()), "non_ascii": share(lambda c: c >= 128),
        }

    for text in ("One two, two. Three!", "a", "x" * 3000, "Ünï cödé | 12\n\nUnder|the bar\nUnder|the bar\n", "\t\n end ", "A? b! c."):
        assert dict(zip(quality.NAMES, quality.statistics(text.encode()), strict=True)) == pytest.approx(plain(text.encode()))
    assert quality.statistics(b"") == quality.statistics(b" \n") == [0.0] * len(quality.NAMES)


def test_discriminant_matches_densities():
    rng = np.random.default_rng(1)
    x0, x1 = rng.normal(0, 1, (400, 3)), rng.normal(1, 2, (400, 3))
    counts = np.array([400.0, 400.0])
    model = quality.solve(counts, np.stack([x0.sum(0), x1.sum(0)]), np.stack([x0.T @ x0, x1.T @ x1]), np.zeros(3))
    z = (x1[:5] - model.centre) / model.scale
    log = []
    for k in (0, 1):
        cov = model.factors[k] @ model.factors[k].T
        d = z - model.means[k]
        log.append(model.priors[k] - 0.5 * np.linalg.slogdet(cov)[1] - 0.5 * np.einsum("ij,jk,ik->i", d, np.linalg.inv(cov), d))
    assert np.allclose(model.score(x1[:5]), 1 / (1 + np.exp(log[0] - log[1])))
