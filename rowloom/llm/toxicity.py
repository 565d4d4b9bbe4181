"""Toxicity by a factorization machine over hashed terms: linear weights and, through low-rank
factors, weights for every pair of terms."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import clear_labels, held_out, lean, release, utf8

WORD = re.compile(rb"[a-z\x80-\xff]+")
FOLDS, FOLD, REJECT = 5, 0, 0.5
#: Buckets that terms are hashed to; a word gives itself and its first bytes as terms.
BUCKETS, PREFIX = 1 << 20, 4
#: Labelled rows learnt from at most, smallest hashes of the id first (the documented bound).
SAMPLE_ROWS = 20_000
#: Buckets that the model keeps at most, and the rank of the factors.
KEPT, RANK = 4096, 8
#: Most frequent buckets whose pairs are tested, and rows of one product of their counts.
PAIRED, PAIR_ROWS = 1024, 2000
#: A pair counts if its chi-square is this many times those of its two buckets alone.
PAIR_GAIN = 4.0
#: Mini-batches of a fit at least, and rows of one.
STEPS, BATCH = 1500, 256
_CACHE = 100_000


class TermBuckets(dict):
    """Word to its buckets; frequent words stay, up to a fixed number of entries."""

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        if len(self) >= _CACHE:
            self.clear()
        mask = BUCKETS - 1
        got = (xxhash.xxh3_64_intdigest(word) & mask,)
        if len(word) > PREFIX:
            got += (xxhash.xxh3_64_intdigest(word[:PREFIX] + b"*") & mask,)
        if len(word) <= 48:
            self[word] = got
        return got


def term_buckets(text: bytes, cache: TermBuckets) -> np.ndarray:
    """Distinct buckets of the words (letters and non-ASCII bytes, A-Z lower-cased) of a whole text."""
    words = set(WORD.findall(text.lower()))
    return np.unique(np.fromiter((b for w in words for b in cache[w]), "int32"))


@dataclass
class FactorizationMachine:
    """score = sigmoid(bias + sum w_i + sum_{i<j} <v_i, v_j>) over the kept buckets of a text."""

    buckets: np.ndarray
    bias: float
    weights: np.ndarray
    factors: np.ndarray

    def score(self, rows: np.ndarray) -> float:
        """`rows`: positions of the text's distinct kept buckets."""
        total = self.bias
        if len(rows):
            v = self.factors[rows]
            s = v.sum(axis=0)
            total += self.weights[rows].sum() + 0.5 * float((s * s).sum() - (v * v).sum())
        return float(1.0 / (1.0 + np.exp(-np.clip(total, -60.0, 60.0))))


def _chi_square(seen: np.ndarray, pos: np.ndarray, n: float, p: float) -> np.ndarray:
    """Chi-square of a presence seen in `seen` of n rows, `pos` of them among the p positive ones; 0 under three rows."""
    gap = pos * n - seen * p
    with np.errstate(divide="ignore", invalid="ignore"):
        chi = np.where(seen >= 3, gap * gap * n / (seen * (n - seen) * p * (n - p)), 0.0)
    return np.nan_to_num(chi, posinf=0.0)


def _noise(tested: int) -> float:
    """About the largest chi-square that chance gives over so many tests."""
    return 2.0 * np.log(max(2, tested)) + 4.0


def select_buckets(rows: list[np.ndarray], labels: np.ndarray) -> np.ndarray:
    """The KEPT buckets at most that tell most about the label, alone or in a pair.

    Alone: by the chi-square of their presence, over rows with three or more. In a pair, for the
    PAIRED most frequent: by the chi-square of the presence of both, where it is far above those of
    either alone, so that what tells only together stays. Both must pass what chance gives over all tested."""
    flat = np.concatenate([np.empty(0, "int32"), *rows])
    of = np.repeat(labels, [len(r) for r in rows])
    seen = np.bincount(flat, minlength=BUCKETS).astype(float)
    pos = np.bincount(flat, weights=of, minlength=BUCKETS)
    n, p = float(len(labels)), float(labels.sum())
    chi = _chi_square(seen, pos, n, p)
    noise = _noise(int((seen >= 3).sum()))

    frequent = np.sort(np.argsort(-seen, kind="stable")[:PAIRED])
    frequent = frequent[seen[frequent] >= 3]
    place = np.full(BUCKETS, -1, "int32")
    place[frequent] = np.arange(len(frequent))
    both, good = np.zeros((2, len(frequent), len(frequent)), np.float32)
    for at in range(0, len(rows), PAIR_ROWS):
        part = rows[at : at + PAIR_ROWS]
        x = np.zeros((len(part), len(frequent)), np.float32)
        for i, r in enumerate(part):
            cols = place[r]
            x[i, cols[cols >= 0]] = 1
        both += x.T @ x
        good += x.T @ (x * labels[at : at + PAIR_ROWS, None].astype(np.float32))
    pair = np.triu(_chi_square(both.astype(float), good.astype(float), n, p), 1)
    alone = np.maximum(chi[frequent][:, None], chi[frequent][None, :])
    i, j = np.nonzero((pair > _noise(pair.size // 2)) & (pair > PAIR_GAIN * alone))
    score = chi.copy()
    score[chi <= noise] = 0.0
    np.maximum.at(score, frequent[i], pair[i, j])
    np.maximum.at(score, frequent[j], pair[i, j])
    best = np.argsort(-score, kind="stable")[:KEPT]
    return np.sort(best[score[best] > 0]).astype("int32")


def fit(
    rows: list[np.ndarray], labels: np.ndarray, epochs: int = 12, rate: float = 0.1, decay: float = 2e-5, seed: int = 7, rank: int = RANK
) -> FactorizationMachine:
    """Mini-batch AdaGrad on the logistic loss; one class only, or no row, gives a constant score.

    Rank 0 is the linear model, for comparison."""
    labels = np.asarray(labels, float)
    kept = select_buckets(rows, labels) if len(rows) else np.empty(0, "int32")
    rate0 = (labels.sum() + 0.5) / (len(labels) + 1.0)
    bias = float(np.log(rate0 / (1 - rate0)))
    w = np.zeros(len(kept))
    v = np.random.default_rng(seed).normal(0, 0.02, (len(kept), rank))
    if not len(kept) or labels.min() == labels.max():
        return FactorizationMachine(kept, bias, w, v * 0)
    place = np.full(BUCKETS, -1, "int32")
    place[kept] = np.arange(len(kept))
    cols = [p[p >= 0] for p in (place[r] for r in rows)]
    gw, gv, gb = np.full_like(w, 1e-6), np.full_like(v, 1e-6), 1e-6
    rng = np.random.default_rng(seed)
    batches = -(-len(cols) // BATCH)
    for _ in range(max(epochs, -(-STEPS // batches))):
        for batch in np.array_split(rng.permutation(len(cols)), batches):
            sizes = np.array([len(cols[i]) for i in batch])
            flat = np.concatenate([cols[i] for i in batch]).astype("int64")
            of = np.repeat(np.arange(len(batch)), sizes)
            vf = v[flat]
            sums = np.zeros((len(batch), rank))
            np.add.at(sums, of, vf)
            squares = np.bincount(of, weights=(vf * vf).sum(axis=1), minlength=len(batch))
            z = bias + np.bincount(of, weights=w[flat], minlength=len(batch)) + 0.5 * ((sums * sums).sum(axis=1) - squares)
            err = 1.0 / (1.0 + np.exp(-np.clip(z, -60, 60))) - labels[batch]
            touched, back = np.unique(flat, return_inverse=True)
            dw = np.bincount(back, weights=err[of]) / len(batch) + decay * w[touched]
            part = err[of, None] * (sums[of] - vf)
            dv = np.zeros((len(touched), rank))
            for k in range(rank):
                dv[:, k] = np.bincount(back, weights=part[:, k])
            dv = dv / len(batch) + decay * v[touched]
            gw[touched] += dw * dw
            gv[touched] += dv * dv
            w[touched] -= rate * dw / np.sqrt(gw[touched])
            v[touched] -= 0.3 * rate * dv / np.sqrt(gv[touched])
            db = err.mean()
            gb += db * db
            bias -= rate * db / np.sqrt(gb)
    return FactorizationMachine(kept, float(bias), w, v)


def chosen_labels(labels: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """(label_id, label) of at most `rows` labelled ids outside the held-out fold, smallest id hashes first.

    A bound on the hash, from a count, lets little more than `rows` reach the sort, however many tasks there are."""
    known = clear_labels(labels, "toxic", FOLDS, FOLD)
    unit = F.pmod(F.xxhash64("label_id"), F.lit(1 << 52))
    total = known.count()
    if total > rows:
        known = known.where(unit < F.lit(int((rows + 8 * rows**0.5 + 100) / total * (1 << 52))))
    return known.orderBy(unit, "label_id").limit(rows)


def train(
    docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", rank: int = RANK
) -> FactorizationMachine:
    """Learns from at most SAMPLE_ROWS labelled ids outside the held-out fold.

    The chosen ids are broadcast (a bounded table); only bucket lists of their texts reach the
    driver, one for each id: of rows that repeat an id, that with the smallest list of buckets."""
    chosen = chosen_labels(labels)
    texts = docs.select(F.col(id_col).cast("long").alias("label_id"), utf8(text_col).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = TermBuckets()
        for batch in batches:
            lists = [term_buckets(t, cache) for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([x.tobytes() for x in lists], pa.binary())],
                names=["label_id", "label", "terms"],
            )

    got = (
        texts.join(F.broadcast(chosen), "label_id")
        .select("label_id", "label", "text")
        .mapInArrow(lean(run), "label_id long, label int, terms binary")
        .groupBy("label_id")
        .agg(F.first("label").alias("label"), F.min("terms").alias("terms"))
        .toPandas()
        .sort_values("label_id", kind="stable")
    )
    return fit([np.frombuffer(t, "int32") for t in got["terms"]], got["label"].to_numpy("float64"), rank=rank)


def _scorer(model: FactorizationMachine) -> Callable[[bytes], float]:
    """Scores of whole texts, with each frequent word's kept buckets remembered."""
    place = dict(zip(model.buckets.tolist(), range(len(model.buckets)), strict=True))

    class Places(TermBuckets):
        def __missing__(self, word: bytes) -> tuple[int, ...]:
            got = tuple(place[b] for b in TermBuckets.__missing__(self, word) if b in place)
            if len(word) <= 48:
                self[word] = got
            return got

    cache = Places()

    def of(text: bytes) -> float:
        rows = {p for w in set(WORD.findall(text.lower())) for p in cache[w]}
        return model.score(np.fromiter(sorted(rows), "int64", len(rows)))

    return of


def score(
    docs: DataFrame, model: FactorizationMachine, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, held_out, score, predicted for every row. Null and empty texts have no terms and get
    the model's base rate; ids may be null (then not held out) or repeat; extra columns are ignored."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = _scorer(model)
        for batch in batches:
            scores = [of(cell.as_py()) for cell in batch.column(2)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(scores, pa.float64()), pa.array([int(s >= REJECT) for s in scores], pa.int32())],
                names=["doc_id", "held_out", "score", "predicted"],
            )

    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text"))
    return own.select("doc_id", held_out("doc_id", FOLDS, FOLD).alias("held_out"), "text").mapInArrow(
        lean(run), "doc_id long, held_out boolean, score double, predicted int"
    )


def keep(docs: DataFrame, model: FactorizationMachine, text_col: str = "text") -> DataFrame:
    """The rows of `docs`, all their columns, that score under 0.5."""

    @F.pandas_udf("double")
    def probability(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        of = _scorer(model)
        for text in texts:
            yield pd.Series([of(t) for t in text], dtype="float64")
        release()

    return docs.where(probability(utf8(text_col)) < F.lit(REJECT))
