"""Language-model scores: word counts with add-one smoothing, and the marginal probability of a
text over all its segmentations into pieces of an existing subword vocabulary.

A piece never crosses a word start, so a text's lattice is a chain of word lattices: a word's
marginal is computed once for each distinct word of the corpus, by a forward recursion in log
space, and a text's is their sum. The vocabulary's own scores are merge ranks, not probabilities:
its pieces are weighted by how often they are expected over all segmentations of the training words,
a step of expectation maximisation from the counts of the best segmentations, with one added to each."""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.pieces import SPACE, codec
from rowloom.llm.shared import held_out, utf8, written

FOLDS, FOLD = 7, 2
#: Most frequent words, at most this many, whose figures are shipped to the tasks; others are joined.
HEAD_WORDS = 1 << 18
#: Distinct words that a task counts before it passes them on.
COUNTED = 300_000
#: Parts of one occurrence that expected counts are summed in: integers, so that no order of tasks matters.
PARTS = 1 << 16
_LOG10 = math.log(10.0)


def tokens(text: bytes) -> list[bytes]:
    """Lower-cased (A-Z) words between space, tab, LF, VT, FF and CR."""
    return text.lower().split()


@dataclass
class PieceModel:
    """Natural-log weights of pieces, single bytes and the end of a text."""

    weights: dict[str, float]
    byte_weights: list[float]
    end: float

    def __post_init__(self) -> None:
        #: Weights of pieces, and None for what only starts pieces.
        self.table: dict[str, float | None] = {p[:i]: None for p in self.weights for i in range(1, len(p))} | self.weights
        self.chances = {p: None if w is None else math.exp(w) for p, w in self.table.items()}
        self.byte_chances = [math.exp(w) for w in self.byte_weights]

    def word(self, word: bytes) -> float:
        """log marginal of a space mark and the word over all segmentations. Every character may also
        be its bytes, whether pieces start with it or not."""
        text = SPACE + word.decode("utf-8", "replace")
        n = len(text)
        find, none = self.table.get, 0
        arriving: list[list[float]] = [[] for _ in range(n + 1)]
        arriving[0].append(0.0)
        for i in range(n):
            terms = arriving[i]
            top = max(terms)
            here = top if len(terms) == 1 else top + math.log(math.fsum([math.exp(t - top) for t in terms]))
            for j in range(i + 1, n + 1):
                weight = find(text[i:j], none)
                if weight is none:
                    break
                if weight is not None:
                    arriving[j].append(here + weight)
            arriving[i + 1].append(here + sum([self.byte_weights[b] for b in text[i].encode()]))
        terms = arriving[n]
        top = max(terms)
        return top + math.log(math.fsum([math.exp(t - top) for t in terms]))


    def shares(self, word: bytes) -> list[tuple[str | int, float]]:
        """The share of all segmentations' probability that passes each arc of the lattice, with the arc's piece (a byte's value)."""
        text = SPACE + word.decode("utf-8", "replace")
        n = len(text)
        find, none = self.chances.get, 0
        forward, backward = [0.0] * (n + 1), [0.0] * (n + 1)
        forward[0] = backward[n] = 1.0
        arcs: list[tuple[int, int, float, str | None]] = []
        for i in range(n):
            here = forward[i]
            chance = 1.0
            for b in text[i].encode():
                chance *= self.byte_chances[b]
            arcs.append((i, i + 1, chance, None))
            forward[i + 1] += here * chance
            for j in range(i + 1, n + 1):
                part = text[i:j]
                chance = find(part, none)
                if chance is none:
                    break
                if chance is not None:
                    arcs.append((i, j, chance, part))
                    forward[j] += here * chance
        whole = forward[n]
        if whole < 1e-250:
            return self._far_shares(text)
        out: list[tuple[str | int, float]] = []
        # arcs rise by their start, so from behind all arcs that leave an arc's end are done
        for i, j, chance, part in reversed(arcs):
            onward = chance * backward[j]
            backward[i] += onward
            share = forward[i] * onward / whole
            if part is None:
                out += [(b, share) for b in text[i].encode()]
            else:
                out.append((part, share))
        return out

    def _far_shares(self, text: str) -> list[tuple[str | int, float]]:
        """`shares` in log space, for words so long that their probabilities vanish."""
        n = len(text)
        find, none = self.table.get, 0
        arcs: list[tuple[int, int, float, str | None]] = []
        arriving: list[list[float]] = [[] for _ in range(n + 1)]
        forward, backward = [0.0] * (n + 1), [0.0] * (n + 1)
        for i in range(n):
            if i:
                forward[i] = _log_sum(arriving[i])
            arcs.append((i, i + 1, sum([self.byte_weights[b] for b in text[i].encode()]), None))
            arriving[i + 1].append(forward[i] + arcs[-1][2])
            for j in range(i + 1, n + 1):
                part = text[i:j]
                weight = find(part, none)
                if weight is none:
                    break
                if weight is not None:
                    arcs.append((i, j, weight, part))
                    arriving[j].append(forward[i] + weight)
        whole = _log_sum(arriving[n])
        out: list[tuple[str | int, float]] = []
        at = len(arcs)
        for i in range(n - 1, -1, -1):
            first = at
            while first and arcs[first - 1][0] == i:
                first -= 1
            backward[i] = _log_sum([w + backward[j] for _, j, w, _ in arcs[first:at]])
            for _, j, w, part in arcs[first:at]:
                share = math.exp(forward[i] + w + backward[j] - whole)
                out += [(unit, share) for unit in (text[i].encode() if part is None else (part,))]
            at = first
        return out


def _log_sum(terms: list[float]) -> float:
    if len(terms) == 1:
        return terms[0]
    top = max(terms)
    return top + math.log(math.fsum([math.exp(t - top) for t in terms]))


def piece_model(model: bytes, counts: np.ndarray, texts: float) -> PieceModel:
    """Weights from the (expected) training counts of all pieces and the number of training texts."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    proto = pb.ModelProto()
    proto.ParseFromString(model)
    kinds = pb.ModelProto.SentencePiece
    total = math.log(float(counts.sum()) + texts + len(proto.pieces) + 1)
    weights, single = {}, [0.0] * 256
    for i, p in enumerate(proto.pieces):
        w = math.log(float(counts[i]) + 1) - total
        if p.type == kinds.BYTE:
            single[int(p.piece[1:-1], 16)] = w
        elif p.type in (kinds.NORMAL, kinds.USER_DEFINED):
            weights[p.piece] = w
    return PieceModel(weights, single, math.log(texts + 1) - total)


def piece_places(model: bytes) -> dict[str | int, int]:
    """Ids of ordinary pieces by their text and of bytes by their value."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    proto = pb.ModelProto()
    proto.ParseFromString(model)
    kinds = pb.ModelProto.SentencePiece
    out: dict[str | int, int] = {}
    for i, p in enumerate(proto.pieces):
        if p.type == kinds.BYTE:
            out[int(p.piece[1:-1], 16)] = i
        elif p.type in (kinds.NORMAL, kinds.USER_DEFINED):
            out[p.piece] = i
    return out


@lru_cache(maxsize=2)
def _cached(model: bytes, counts: bytes, texts: int) -> PieceModel:
    return piece_model(model, np.frombuffer(counts, "float64"), texts)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Occurrences of words in all and in training texts."""
    every: Counter[bytes] = Counter()
    learnt: Counter[bytes] = Counter()

    def flush() -> pa.RecordBatch:
        words = list(every)
        out = pa.RecordBatch.from_arrays(
            [
                pa.array(words, pa.binary()),
                pa.array([every[w] for w in words], pa.int64()),
                pa.array([learnt.get(w, 0) for w in words], pa.int64()),
            ],
            names=["word", "n", "c"],
        )
        every.clear()
        learnt.clear()
        return out

    for batch in batches:
        for held, cell in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
            words = tokens(cell.as_py())
            every.update(words)
            if not held:
                learnt.update(words)
            if len(every) >= COUNTED:
                yield flush()
    if every:
        yield flush()


def _piece_counts(model: bytes):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model)
        total = np.zeros(own.library.get_piece_size(), "int64")
        for batch in batches:
            words = [w.decode("utf-8", "replace") for w in batch.column(0).to_pylist()]
            for ids, c in zip(own.library.encode(words, num_threads=1), batch.column(1).to_pylist(), strict=True):
                for i in ids:
                    total[i] += c
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype("int32")), pa.array(total[some])], names=["piece", "c"])

    return run


def _expected_counts(model: bytes, counts: bytes, texts: int):  # noqa: ANN202
    """Expected occurrences of pieces over all segmentations of the words, in PARTS."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, place = _cached(model, counts, texts), piece_places(model)
        total = [0] * codec(model).library.get_piece_size()
        for batch in batches:
            for word, c in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for piece, share in own.shares(word):
                    parts = int(share * PARTS + 0.5)
                    if parts:
                        total[place[piece]] += parts * c
        some = [i for i, x in enumerate(total) if x]
        yield pa.RecordBatch.from_arrays(
            [pa.array(some, pa.int32()), pa.array([str(total[i]) for i in some], pa.string())], names=["piece", "parts"]
        )

    return run


def _marginals(model: bytes, counts: bytes, texts: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = _cached(model, counts, texts)
        for batch in batches:
            words = batch.column(0).to_pylist()
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array([own.word(w) for w in words], pa.float64())], names=["word", "c", "lm"]
            )

    return run


def _texts(head: dict[bytes, tuple[float, float, int]]):  # noqa: ANN202
    """Sums over the shipped words of each text, and its other words with their counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        get = head.get
        for batch in batches:
            for part in (batch.slice(i, 512) for i in range(0, batch.num_rows, 512)):
                rows = []
                for cell in part.column(2):
                    found = Counter(tokens(cell.as_py()))
                    base = lm = 0.0
                    known = total = 0
                    others, times = [], []
                    for w, k in found.items():
                        total += k
                        got = get(w)
                        if got is None:
                            others.append(w)
                            times.append(k)
                        else:
                            base += k * got[0]
                            lm += k * got[1]
                            known += k * got[2]
                    rows.append((total, known, base, lm, others, times))
                types = [pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.binary()), pa.list_(pa.int32())]
                columns = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)]
                names = ["doc_id", "held_out", "words", "known", "base", "lm", "others", "times"]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *columns], names=names)

    return run


def lattice_scores(
    docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", head_words: int = HEAD_WORDS
) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row.

    Learns from rows whose crc32(id as text) mod 7 is not 2 (rows without an id too). Tokens are
    words and one end for each text; base_score is the sum of log10((c + 1) / (N + V + 1)), score
    the log10 marginal of the text under the piece model, its end included. Null and empty texts
    are only an end. With no training text all counts are 0. Ids may repeat; extra columns are
    ignored. Shipped to tasks: the model file, 32 thousand piece counts, and at most `head_words` words of up to 64 bytes; all other words meet
    their counts in a join by word, none of which is frequent."""
    model = Path(model_path).read_bytes()
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text")).select(
        "doc_id", held_out("doc_id", FOLDS, FOLD).alias("held_out"), "text"
    )
    words = written(
        rows.mapInArrow(_count, "word binary, n long, c long").groupBy("word").agg(F.sum("n").alias("n"), F.sum("c").alias("c")),
        "words",
    )
    texts = rows.select("held_out").where("not held_out").count()
    facts = words.agg(F.sum("c").alias("c"), F.count_if(F.col("c") > 0).alias("v")).first()
    train_tokens = (facts["c"] or 0) + texts
    vocabulary = facts["v"] + (texts > 0)
    below = math.log10(train_tokens + vocabulary + 1)

    counts = np.zeros(codec(model).library.get_piece_size(), "int64")
    got = words.where("c > 0").select("word", "c").mapInArrow(_piece_counts(model), "piece int, c long")
    for r in got.groupBy("piece").agg(F.sum("c").alias("c")).collect():
        counts[r["piece"]] = r["c"]
    # one step of expectation maximisation from the best segmentations' counts
    parts = [0] * len(counts)
    start = counts.astype("float64").tobytes()
    got = words.where("c > 0").select("word", "c").mapInArrow(_expected_counts(model, start, texts), "piece int, parts string")
    for r in got.groupBy("piece").agg(F.sum(F.col("parts").cast("decimal(38,0)")).alias("parts")).collect():
        parts[r["piece"]] = int(r["parts"])
    counts = np.array([x / PARTS for x in parts])
    marginals = _marginals(model, counts.tobytes(), texts)
    kind = "word binary, c long, lm double"

    # how many words have each order of magnitude of occurrences: at most 8 steps for each doubling
    steps = sorted(
        words.groupBy(F.floor(F.log2("n") * 8).alias("step")).agg(F.count("*").alias("words")).collect(), key=lambda r: -r["step"]
    )
    floor, room = float("inf"), head_words
    for r in steps:
        room -= r["words"]
        if room < 0:
            break
        floor = r["step"]
    is_head = (F.floor(F.log2("n") * 8) >= F.lit(floor)) & (F.length("word") <= 64)
    head = {
        bytes(r["word"]): (math.log10(r["c"] + 1), r["lm"] / _LOG10, int(r["c"] > 0))
        for r in words.where(is_head).select("word", "c").mapInArrow(marginals, kind).toLocalIterator()
    }
    tail = words.where(~is_head).select("word", "c").mapInArrow(marginals, kind).select(
        "word", F.log10(F.col("c") + 1.0).alias("t_base"), (F.col("lm") / _LOG10).alias("t_lm"), (F.col("c") > 0).cast("long").alias("t_known")
    )

    summed = written(
        rows.mapInArrow(
            _texts(head),
            "doc_id long, held_out boolean, words long, known long, base double, lm double, others array<binary>, times array<int>",
        ).withColumn("row", F.monotonically_increasing_id()),
        "texts",
    )
    parts = (
        summed.select("row", F.explode(F.arrays_zip("others", "times")).alias("t"))
        .select("row", F.col("t.others").alias("word"), F.col("t.times").alias("k"))
        .join(tail.hint("merge"), "word")
        .groupBy("row")
        .agg(F.sum(F.col("k") * F.col("t_base")).alias("base"), F.sum(F.col("k") * F.col("t_lm")).alias("lm"), F.sum(F.col("k") * F.col("t_known")).alias("known"))
    )
    own = summed.select("row", "doc_id", "held_out", "words", "base", "lm", "known")
    none = [F.lit(None).cast(t).alias(c) for c, t in (("doc_id", "long"), ("held_out", "boolean"), ("words", "long"))]
    end_base = math.log10(texts + 1)
    end_lm = (math.log(texts + 1) - math.log(float(counts.sum()) + texts + len(counts) + 1)) / _LOG10
    n = F.col("words") + 1
    return (
        own.union(parts.select("row", *none, "base", "lm", "known"))
        .groupBy("row")
        .agg(
            F.max("doc_id").alias("doc_id"), F.max("held_out").alias("held_out"), F.max("words").alias("words"),
            F.sum("base").alias("base"), F.sum("lm").alias("lm"), F.sum("known").alias("known"),
        )
        .select(
            "doc_id", "held_out", n.alias("n_tokens"), (F.col("known") + int(texts > 0)).alias("n_known"),
            F.lit(train_tokens).cast("long").alias("train_tokens"),
            (F.col("base") + end_base - n * below).alias("base_score"), (F.col("lm") + end_lm).alias("score"),
        )
    )
