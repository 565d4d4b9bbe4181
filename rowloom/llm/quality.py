"""Quality by a regularised quadratic discriminant over transformed document statistics."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import clear_labels, held_out, lean, release, utf8

FOLDS, FOLD, ACCEPT = 5, 0, 0.3
#: Part of the pooled covariance in each class covariance, and of a scaled identity in both.
POOLED, RIDGE = 0.3, 0.02

#: The statistics, in the order of `statistics`.
NAMES = (
    "log_bytes", "log_words", "word_length", "word_spread", "longest_word", "upper", "digit", "punct", "marks",
    "bars", "lines", "line_length", "repeat_word", "same_next", "repeat_line", "stops", "char_entropy", "non_ascii",
)

_CLASS = np.zeros(256, "int64")
_CLASS[ord("A") : ord("Z") + 1] = 1
_CLASS[ord("0") : ord("9") + 1] = 2
for _c in b".,;:?'\"-()":
    _CLASS[_c] = 3
for _c in b"!#$%&*+/<=>@[\\]^_`{}~":
    _CLASS[_c] = 4
_CLASS[ord("|")] = 5
_CLASS[128:] = 6


def statistics(text: bytes) -> list[float]:
    """Bounded, roughly symmetric statistics of a whole text; an empty text gives zeros."""
    words = text.split()
    n, m = len(text), len(words)
    if not m:
        return [0.0] * len(NAMES)
    counts = np.bincount(np.frombuffer(text, "u1"), minlength=256)
    kinds = np.bincount(_CLASS, weights=counts, minlength=7)
    sizes = np.fromiter(map(len, words), "int64", m)
    lines = [x for x in text.split(b"\n") if x.strip()]
    share = counts[counts > 0] / n
    same = sum(map(bytes.__eq__, words[1:], words[:-1]))
    ends = sum(w[-1] in b".!?" for w in words)
    root = lambda x: float(np.sqrt(x))
    return [
        float(np.log1p(n)),
        float(np.log1p(m)),
        float(np.log(sizes.mean())),
        float(np.log1p(sizes.std())),
        float(np.log(min(int(sizes.max()), 1000))),
        root(kinds[1] / n),
        root(kinds[2] / n),
        root(kinds[3] / n),
        root(kinds[4] / n),
        root(kinds[5] / n),
        float(np.log1p(len(lines))),
        float(np.log1p(n / len(lines))),
        root(1.0 - len(set(words)) / m),
        root(same / m),
        root(1.0 - len(set(lines)) / len(lines)),
        root(ends / m),
        float(-(share * np.log2(share)).sum()),
        root(kinds[6] / n),
    ]


#: Sums are taken about the statistics of an ordinary sentence, so that second moments do not cancel.
ORIGIN = np.array(statistics(b"The first of many ordinary sentences, with a few common words in it.\nAnd a second one.\n"))


@dataclass
class Discriminant:
    """Class means, Cholesky factors of their shrunken covariances, and log priors."""

    means: np.ndarray
    factors: np.ndarray
    priors: np.ndarray
    centre: np.ndarray
    scale: np.ndarray

    def __post_init__(self) -> None:
        # cached once: inverse factors for Mahalanobis distances and log determinants
        self.inverse = np.stack([np.linalg.inv(c) for c in self.factors])
        self.half_logdet = np.log(np.stack([np.diag(c) for c in self.factors])).sum(axis=1)

    def score(self, x: np.ndarray) -> np.ndarray:
        """Posterior of class 1 for rows of statistics."""
        z = np.clip((x - self.centre) / self.scale, -8.0, 8.0)
        log = [
            self.priors[k] - self.half_logdet[k] - 0.5 * (((z - self.means[k]) @ self.inverse[k].T) ** 2).sum(axis=1)
            for k in (0, 1)
        ]
        return 1.0 / (1.0 + np.exp(np.clip(log[0] - log[1], -60.0, 60.0)))


def solve(counts: np.ndarray, sums: np.ndarray, products: np.ndarray, origin: np.ndarray) -> Discriminant:
    """The discriminant of per-class counts, sums and sums of outer products about `origin`. A class
    without rows gets the pooled moments."""
    d = sums.shape[1]
    n = counts.sum()
    centre = sums.sum(axis=0) / max(n, 1.0)
    total = products.sum(axis=0) / max(n, 1.0) - np.outer(centre, centre)
    scale = np.sqrt(np.maximum(np.diag(total), 1e-6))
    pooled, means, own = np.zeros((d, d)), np.zeros((2, d)), np.zeros((2, d, d))
    for k in (0, 1):
        if counts[k]:
            mu = sums[k] / counts[k]
            means[k] = (mu - centre) / scale
            own[k] = (products[k] / counts[k] - np.outer(mu, mu)) / np.outer(scale, scale)
            pooled += own[k] * counts[k] / n
    factors = []
    for k in (0, 1):
        weight = POOLED if counts[k] > d else 1.0
        cov = (1 - weight) * own[k] + weight * pooled
        cov = (1 - RIDGE) * cov + RIDGE * max(np.trace(cov) / d, 1e-3) * np.eye(d)
        factors.append(np.linalg.cholesky(cov + 1e-9 * np.eye(d)))
    priors = np.log((counts + 1.0) / (n + 2.0))
    return Discriminant(means, np.stack(factors), priors, origin + centre, scale)


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Discriminant:
    """Learns from all labelled rows outside the held-out fold: each task sends its sums, nothing else.

    The join is on the id, with map-side work on neither side; Spark picks its form by size."""
    known = clear_labels(labels, "quality", FOLDS, FOLD)
    texts = docs.select(F.col(id_col).cast("long").alias("label_id"), utf8(text_col).alias("text"))
    d = len(NAMES)

    def facts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [np.array(statistics(t)).tobytes() for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.binary())], names=["label_id", "x"])

    def moments(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums = np.zeros((2, 1 + d + d * d))
        for pdf in batches:
            y = pdf["label"].to_numpy()
            x = np.frombuffer(b"".join(pdf["x"]), "float64").reshape(len(pdf), d) - ORIGIN
            for k in (0, 1):
                z = x[y == k]
                sums[k] += np.concatenate([[len(z)], z.sum(axis=0), (z.T @ z).ravel()])
        yield pd.DataFrame({"label": [0, 1], "sums": [s.tolist() for s in sums]})

    parts = (
        texts.where("label_id is not null")
        .where(~held_out("label_id", FOLDS, FOLD))
        .mapInArrow(lean(facts), "label_id long, x binary")
        .join(known, "label_id")
        .select("label", "x")
        .mapInPandas(moments, "label int, sums array<double>")
        .select("label", F.posexplode("sums").alias("i", "v"))
        .groupBy("label", "i")
        .agg(F.sum("v").alias("v"))
        .toPandas()
    )
    grid = np.zeros((2, 1 + d + d * d))
    grid[parts["label"].to_numpy("int64"), parts["i"].to_numpy("int64")] = parts["v"]
    return solve(grid[:, 0], grid[:, 1 : 1 + d], grid[:, 1 + d :].reshape(2, d, d), ORIGIN)


def score(docs: DataFrame, model: Discriminant, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted (score >= 0.3) for every row. Null and empty texts have
    zero statistics and are scored as such; ids may be null (then not held out) or repeat; extra
    columns are ignored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array([statistics(c.as_py()) for c in batch.column(2)]).reshape(-1, len(NAMES))
            got = model.score(x)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(got), pa.array((got >= ACCEPT).astype("int32"))],
                names=["doc_id", "held_out", "score", "predicted"],
            )

    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text"))
    return own.select("doc_id", held_out("doc_id", FOLDS, FOLD).alias("held_out"), "text").mapInArrow(
        lean(run), "doc_id long, held_out boolean, score double, predicted int"
    )


def keep(docs: DataFrame, model: Discriminant, text_col: str = "text") -> DataFrame:
    """The rows of `docs`, all their columns, that the classifier accepts."""

    @F.pandas_udf("double")
    def probability(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for text in texts:
            x = np.array([statistics(t) for t in text]).reshape(-1, len(NAMES))
            yield pd.Series(model.score(x))
        release()

    return docs.where(probability(utf8(text_col)) >= F.lit(ACCEPT))
