from __future__ import annotations

import math
import zlib
from collections import Counter

import numpy as np
import pytest

from rowloom.llm import lattice


def brute_marginal(model, text):
    """Sum over all segmentations of the products of their weights."""
    if not text:
        return 1.0
    total = 0.0
    for j in range(1, len(text) + 1):
        if text[:j] in model.weights:
            total += math.exp(model.weights[text[:j]]) * brute_marginal(model, text[j:])
    return total + math.exp(sum(model.byte_weights[b] for b in text[0].encode())) * brute_marginal(model, text[1:])


def test_forward_sum_is_the_marginal():
    rng = np.random.default_rng(5)
    parts = ["▁", "▁a", "a", "ab", "b", "ba", "▁ab", "abb", "é"]
    model = lattice.PieceModel({p: math.log(w) for p, w in zip(parts, rng.dirichlet(np.ones(len(parts))) * 0.9, strict=True)}, [math.log(0.1 / 256)] * 256, -3.0)
    for word in ("", "a", "abba", "bab", "é", "abcé", "aabb"):
        assert math.exp(model.word(word.encode())) == pytest.approx(brute_marginal(model, "▁" + word), rel=1e-9)


def all_segmentations(model, text):
    """(weight, units) of every segmentation."""
    if not text:
        yield 1.0, ()
        return
    for j in range(1, len(text) + 1):
        if text[:j] in model.weights:
            for w, units in all_segmentations(model, text[j:]):
                yield w * math.exp(model.weights[text[:j]]), (text[:j], *units)
    own = text[0].encode()
    for w, units in all_segmentations(model, text[1:]):
        yield w * math.exp(sum(model.byte_weights[b] for b in own)), (*own, *units)


def test_expected_counts_are_those_over_all_segmentations():
    rng = np.random.default_rng(6)
    parts = ["▁", "▁a", "a", "ab", "b", "ba", "▁ab", "abb", "é"]
    model = lattice.PieceModel({p: math.log(w) for p, w in zip(parts, rng.dirichlet(np.ones(len(parts))) * 0.9, strict=True)}, [math.log(0.1 / 256)] * 256, -3.0)
    for word in ("", "a", "abba", "bab", "é", "abcé"):
        want, total = Counter(), 0.0
        for w, units in all_segmentations(model, "▁" + word):
            total += w
            for u in units:
                want[u] += w
        for shares in (model.shares(word.encode()), model._far_shares("▁" + word)):
            got = Counter()
            for unit, share in shares:
                got[unit] += share
            assert dict(got) == pytest.approx({u: x / total for u, x in want.items()}, rel=1e-9)
    far = model.shares(b"ab" * 3000)
    assert sum(share * (len(unit) if isinstance(unit, str) else 1) for unit, share in far if unit not in range(0x80, 0x100)) > 5990


def test_expectation_step_raises_the_likelihood(model_path, documents):
    """The training words are likelier under the expected counts than under those of best segmentations."""
    rows = [(r["doc_id"], r["text"]) for r in documents.limit(40).collect()]
    data = open(model_path, "rb").read()
    counts, texts, words = best_counts(rows, data)
    first, second = lattice.piece_model(data, counts, texts), reference_model(rows, model_path)
    gain = [second.word(w) * c - first.word(w) * c for w, c in words.items()]
    assert sum(gain) > 0


def brute(rows, model, head):
    held = {i: d is not None and zlib.crc32(str(d).encode()) % 7 == 2 for i, (d, _) in enumerate(rows)}
    words = [lattice.tokens((t or "").encode()) for _, t in rows]
    c = Counter()
    train = [i for i in held if not held[i]]
    for i in train:
        c.update(words[i])
    n, v = sum(c.values()) + len(train), len(c) + bool(train)
    out = []
    for i, (d, _) in enumerate(rows):
        base = sum(math.log10((c[w] + 1) / (n + v + 1)) for w in words[i]) + math.log10((len(train) + 1) / (n + v + 1))
        score = (sum(model.word(w) for w in words[i]) + model.end) / math.log(10)
        out.append((str(d), held[i], len(words[i]) + 1, sum(c[w] > 0 for w in words[i]) + bool(train), n, base, score))
    return out


def best_counts(rows, data):
    own = lattice.codec(data)
    counts = np.zeros(own.library.get_piece_size(), "int64")
    texts, words = 0, Counter()
    for d, t in rows:
        if d is None or zlib.crc32(str(d).encode()) % 7 != 2:
            texts += 1
            words.update(lattice.tokens((t or "").encode()))
    for w, c in words.items():
        for i in own.library.encode(w.decode()):
            counts[i] += c
    return counts, texts, words


def reference_model(rows, model_path):
    data = open(model_path, "rb").read()
    counts, texts, words = best_counts(rows, data)
    start, place = lattice.piece_model(data, counts, texts), lattice.piece_places(data)
    parts = [0] * len(counts)
    for w, c in words.items():
        for piece, share in start.shares(w):
            parts[place[piece]] += int(share * lattice.PARTS + 0.5) * c
    return lattice.piece_model(data, np.array([x / lattice.PARTS for x in parts]), texts)


@pytest.mark.parametrize("head", [0, 50, 1 << 18])
def test_scores_match_brute_force(odd_docs, model_path, head):
    rows = [(r["doc_id"], r["text"]) for r in odd_docs.collect()]
    want = sorted(brute(rows, reference_model(rows, model_path), head), key=str)
    got = sorted([(str(r[0]), *tuple(r)[1:]) for r in lattice.lattice_scores(odd_docs, model_path, head_words=head).collect()], key=str)
    assert [g[:5] for g in got] == [w[:5] for w in want]
    assert [g[5] for g in got] == pytest.approx([w[5] for w in want], rel=1e-9)
    assert [g[6] for g in got] == pytest.approx([w[6] for w in want], rel=1e-9)


def test_no_rows(no_docs, model_path):
    assert lattice.lattice_scores(no_docs, model_path).count() == 0
