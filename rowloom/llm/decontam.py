"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

Patterns are the windows of benchmark items. A table of word blocks says how far a search
position may skip, blocks that end a pattern lead to the patterns to test, and a direct
comparison confirms each occurrence."""

from __future__ import annotations

import math
import re
from collections.abc import Callable, Iterator
from functools import partial

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import lean, release, utf8, written

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
WINDOW = 10
#: Benchmark text that one pass searches for; a larger benchmark takes several passes.
PASS_BYTES = 8 << 20


def words_of(text: bytes) -> list[bytes]:
    """Lower-cased (A-Z) maximal stretches of ASCII letters, digits and non-ASCII bytes."""
    return WORD.findall(text.lower())


class WuManber:
    """Search for word sequences of one length."""

    def __init__(self, patterns: dict[tuple[bytes, ...], list[int]], length: int):
        self.length = length
        self.block = min(length, 3 if len(patterns) > 50_000 else 2)
        self.far = length - self.block + 1
        self.head = length - self.block
        self.shift: dict[tuple[bytes, ...], int] = {}
        # a bucket for each last block; in it, patterns by a prefix, so that items that share endings cost no more
        self.suffixes: dict[tuple[bytes, ...], dict[tuple[bytes, ...], list[tuple[bytes, ...]]]] = {}
        self.patterns = patterns
        for p in patterns:
            for end in range(self.block, length + 1):
                key = p[end - self.block : end]
                self.shift[key] = min(self.shift.get(key, self.far), length - end)
            self.suffixes.setdefault(p[length - self.block :], {}).setdefault(p[: self.head], []).append(p)

    def find(self, words: list[bytes]) -> Iterator[tuple[int, tuple[bytes, ...]]]:
        """(first word, pattern) of every occurrence, overlapping ones too."""
        shift, far, m, n = self.shift.get, self.far, self.length, len(words)
        at = m - 1
        if self.block == 2:
            while at < n:
                step = shift((words[at - 1], words[at]), far)
                if step:
                    at += step
                else:
                    yield from self._test(words, at)
                    at += 1
            return
        b = self.block
        while at < n:
            step = shift(tuple(words[at - b + 1 : at + 1]), far)
            if step:
                at += step
            else:
                yield from self._test(words, at)
                at += 1

    def _test(self, words: list[bytes], at: int) -> Iterator[tuple[int, tuple[bytes, ...]]]:
        first = at - self.length + 1
        seen = tuple(words[first : at + 1])
        for p in self.suffixes[seen[self.length - self.block :]].get(seen[: self.head], ()):
            if p == seen:
                yield first, p


class ItemSearch:
    """The windows of a set of items, searched length by length."""

    def __init__(self, items: list[tuple[str | None, bytes]], window: int = WINDOW):
        by: dict[int, dict[tuple[bytes, ...], list[int]]] = {}
        self.names = [name for name, _ in items]
        for k, (_, text) in enumerate(items):
            words = words_of(text)
            size = min(window, len(words))
            for i in range(len(words) - size + 1 if size else 0):
                owners = by.setdefault(size, {}).setdefault(tuple(words[i : i + size]), [])
                if not owners or owners[-1] != k:
                    owners.append(k)
        self.machines = [WuManber(p, size) for size, p in sorted(by.items())]

    def search(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Disjoint covered stretches (first, last word) in order, and the names of occurring items."""
        stretches, owners = [], set()
        for machine in self.machines:
            for first, pattern in machine.find(words):
                stretches.append((first, first + machine.length - 1))
                owners.update(machine.patterns[pattern])
        return merge(stretches), {self.names[k] for k in owners if self.names[k] is not None}


def merge(stretches: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for first, last in sorted(stretches):
        if out and first <= out[-1][1] + 1:
            out[-1] = (out[-1][0], max(out[-1][1], last))
        else:
            out.append((first, last))
    return out


_KIND = "n_words long, spans array<struct<first:int,last:int>>, items array<string>"
_SPANS = pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32())]))


def _pass(items: list[tuple[str | None, bytes]], only_hits: bool):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = ItemSearch(items)
        for batch in batches:
            for part in (batch.slice(i, 512) for i in range(0, batch.num_rows, 512)):
                keep, rows = [], []
                for i, cell in enumerate(part.column(1)):
                    words = words_of(cell.as_py())
                    spans, names = search.search(words)
                    if spans or not only_hits:
                        keep.append(i)
                        rows.append((len(words), [{"first": a, "last": b} for a, b in spans], sorted(names)))
                if rows:
                    columns = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int64(), _SPANS, pa.list_(pa.string())), strict=True)]
                    yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(keep)), *columns], names=["key", "n_words", "spans", "items"])

    return run


def _loads(benchmark: DataFrame, item_col: str, text_col: str, pass_bytes: int) -> list[Callable[[], list[tuple[str | None, bytes]]]]:
    """One loader for each pass, of the items that it searches for."""
    items = benchmark.select(F.col(item_col).cast("string").alias("item"), utf8(text_col).alias("text"))
    total = items.agg(F.sum(F.length("text"))).first()[0] or 0
    passes = max(1, math.ceil(total / pass_bytes))
    dealt = items.withColumn("part", F.pmod(F.xxhash64("item", "text"), F.lit(passes)))

    def load(k: int) -> list[tuple[str | None, bytes]]:
        rows = dealt.where(F.col("part") == k).select("item", "text").collect()
        return sorted(((r["item"], bytes(r["text"])) for r in rows), key=lambda x: (x[0] or "", x[1]))

    return [partial(load, k) for k in range(passes)]


def keep(
    docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id",
    item_text_col: str = "text", pass_bytes: int = PASS_BYTES,
) -> DataFrame:
    """The rows of `docs`, all their columns, without an occurrence of any benchmark window.

    With several passes, each writes the digests of the texts that it hits, and rows with one leave."""
    loads = _loads(benchmark, item_col, item_text_col, pass_bytes)
    if len(loads) == 1:
        return docs.where(_clean(loads[0]())(utf8(text_col)))
    keyed = docs.select(F.sha2(utf8(text_col), 256).alias("key"), utf8(text_col).alias("text"))
    hits = _all_hits(keyed, loads).select(F.col("key").alias("__hit")).distinct()
    return docs.withColumn("__key", F.sha2(utf8(text_col), 256)).join(hits, F.col("__key") == F.col("__hit"), "left_anti").drop("__key")


def _all_hits(keyed: DataFrame, loads: list[Callable[[], list[tuple[str | None, bytes]]]]) -> DataFrame:
    """Hits of all passes. Each pass is written before the next one's items are loaded."""
    hits = None
    for load in loads:
        found = written(keyed.mapInArrow(lean(_pass(load(), True)), f"key string, {_KIND}"), "hits")
        hits = found if hits is None else hits.union(found)
    return hits


def _clean(items: list[tuple[str | None, bytes]]):  # noqa: ANN202
    @F.pandas_udf("boolean")
    def clean(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        machines = ItemSearch(items).machines
        for text in texts:
            yield pd.Series([not any(True for m in machines for _ in m.find(words)) for words in map(words_of, text)], dtype="bool")
        release()

    return clean


def find_contamination(
    docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text",
    item_col: str = "item_id", item_text_col: str = "text", pass_bytes: int = PASS_BYTES,
) -> DataFrame:
    """doc_id, n_words, spans, items for every row of `docs`: the word stretches that lie in an
    occurrence of a benchmark window, and the sorted ids (as strings) of the items it is from.

    Windows have 10 words, shorter items are one window, items without words none. Null and empty
    texts have no words; items without an id count for spans but are not listed; rows may repeat;
    extra columns are ignored. Items are searched in passes of about `pass_bytes` of benchmark
    text, one after another, each shipped to the tasks whole; with one pass nothing is shuffled."""
    loads = _loads(benchmark, item_col, item_text_col, pass_bytes)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text"))
    if len(loads) == 1:
        return texts.mapInArrow(lean(_pass(loads[0](), False)), f"doc_id long, {_KIND}")

    keyed = texts.select(F.sha2("text", 256).alias("key"), "text")
    hits = _all_hits(keyed, loads)

    @F.pandas_udf("array<struct<first:int,last:int>>")
    def joined(spans: pd.Series) -> pd.Series:
        return spans.map(lambda x: [{"first": a, "last": b} for a, b in merge([(int(s["first"]), int(s["last"])) for s in x])])

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = [len(words_of(t)) for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64())], names=["doc_id", "key", "n_words"])

    # each text's stretches and items once, however many rows have that text
    spans = hits.select("key", F.explode("spans").alias("s")).groupBy("key").agg(F.collect_set("s").alias("s"))
    names = hits.select("key", F.explode("items").alias("i")).groupBy("key").agg(F.sort_array(F.collect_set("i")).alias("items"))
    rows = texts.select("doc_id", F.sha2("text", 256).alias("key"), "text").mapInArrow(lean(counted), "doc_id long, key string, n_words long")
    return (
        rows.join(spans.select("key", joined("s").alias("spans")), "key", "left")
        .join(names, "key", "left")
        .select(
            "doc_id", "n_words",
            F.coalesce("spans", F.array().cast("array<struct<first:int,last:int>>")).alias("spans"),
            F.coalesce("items", F.array().cast("array<string>")).alias("items"),
        )
    )


def contamination_digest(found: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated of `find_contamination`'s rows."""
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + (s["last"] - s["first"] + 1).cast("long"))
    return found.select(
        "doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "items").cast("binary"), 256).alias("items_sha256"),
        (F.size("spans") > 0).alias("contaminated"),
    )


__all__ = ["ItemSearch", "WuManber", "contamination_digest", "find_contamination", "merge", "words_of"]
