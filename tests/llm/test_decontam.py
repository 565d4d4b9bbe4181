from __future__ import annotations

from hypothesis import given, settings
from hypothesis import strategies as st

from rowloom.llm import decontam


def brute(words, items, window=10):
    hit, names = set(), set()
    for name, text in items:
        w = decontam.words_of(text)
        size = min(window, len(w))
        for i in range(len(w) - size + 1 if size else 0):
            for k in range(len(words) - size + 1):
                if words[k : k + size] == w[i : i + size]:
                    hit.update(range(k, k + size))
                    if name is not None:
                        names.add(name)
    return hit, names


_TEXT = st.lists(st.sampled_from("a b c dd é".split()), max_size=40).map(" ".join)


@settings(max_examples=120, deadline=None)
@given(_TEXT, st.lists(_TEXT, max_size=4), st.sampled_from([1, 2, 3, 5, 10]))
def test_search_matches_brute_force(doc, items, window):
    named = [(str(i), t.encode()) for i, t in enumerate(items)]
    words = decontam.words_of(doc.encode())
    spans, names = decontam.ItemSearch(named, window).search(words)
    hit, want = brute(words, named, window)
    assert {k for a, b in spans for k in range(a, b + 1)} == hit and names == want


def test_large_pattern_sets_use_longer_blocks():
    patterns = {tuple(f"{i}{j}".encode() for j in range(5)): [i] for i in range(50_001)}
    machine = decontam.WuManber(patterns, 5)
    assert machine.block == 3
    p = list(patterns)[7]
    assert list(machine.find([b"x", *p, b"y"])) == [(1, p)]


def test_items_that_share_an_ending():
    """Thousands of patterns end alike: each place meets those of its own beginning only."""
    patterns = {(*(f"{i}".encode() for _ in range(8)), b"the", b"end"): [i] for i in range(3000)}
    machine = decontam.WuManber(patterns, 10)
    assert [len(bucket) for bucket in machine.suffixes.values()] == [3000]
    assert all(len(own) == 1 for bucket in machine.suffixes.values() for own in bucket.values())
    p = list(patterns)[1234]
    assert list(machine.find([b"x", *p, b"the", b"end"])) == [(1, p)]


def test_odd_rows_and_passes(spark, odd_docs, no_docs):
    items = spark.createDataFrame(
        [(1, "the quick BROWN fox jumps over the lazy dog again", 0), (2, "one two three", 0), (3, None, 0), (None, "no id at all", 0), (2, "one two three", 0), (4, "", 0)],
        "item_id long, text string, doc_id int",
    )
    one = decontam.contamination_digest(decontam.find_contamination(odd_docs, items))
    many = decontam.contamination_digest(decontam.find_contamination(odd_docs, items, pass_bytes=16))
    assert sorted(map(str, one.collect())) == sorted(map(str, many.collect()))
    named = [(None if r["item_id"] is None else str(r["item_id"]), (r["text"] or "").encode()) for r in items.collect()]
    for r in decontam.find_contamination(odd_docs, items).collect():
        texts = [x["text"] or "" for x in odd_docs.where(odd_docs.doc_id.eqNullSafe(r["doc_id"])).collect()]
        hits = [brute(decontam.words_of(t.encode()), named) for t in texts if len(t) < 10_000]
        if hits:
            assert (sum(s["last"] - s["first"] + 1 for s in r["spans"]), set(r["items"])) in [(len(h), n) for h, n in hits]
    kept = decontam.keep(odd_docs, items, pass_bytes=16)
    assert kept.columns == odd_docs.columns
    assert kept.count() == one.where("not contaminated").count()
    assert decontam.find_contamination(no_docs, items).count() == 0
    assert decontam.find_contamination(odd_docs, items.where("false")).where("size(spans) > 0").count() == 0
