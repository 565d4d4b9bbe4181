from __future__ import annotations

from hypothesis import given, settings
from hypothesis import strategies as st

from rowloom.llm import licenses


def naive_statistics(words, templates):
    """Longest template substring that ends at each word."""
    known = {tuple(t[i:j]) for t in templates for i in range(len(t)) for j in range(i + 1, len(t) + 1)}
    out = []
    for i in range(len(words)):
        out.append(max([n for n in range(1, i + 2) if tuple(words[i + 1 - n : i + 1]) in known], default=0))
    return out


@settings(max_examples=80, deadline=None)
@given(st.lists(st.lists(st.integers(0, 3), min_size=1, max_size=8), min_size=1, max_size=4), st.lists(st.integers(0, 4), max_size=30))
def test_matching_statistics(templates, words):
    machine = licenses.SuffixAutomaton(templates)
    state = length = 0
    got = []
    for w in words:
        state, length = machine.step(state, length, w)
        got.append(length)
    assert got == naive_statistics(words, templates)


def test_ends_are_all_occurrences():
    machine = licenses.SuffixAutomaton([[1, 2, 1, 2], [2, 1]])
    state = length = 0
    for w in (2, 1):
        state, length = machine.step(state, length, w)
    assert machine.ends[state] == [(0, 2), (1, 1)]


@settings(max_examples=80, deadline=None)
@given(st.lists(st.sampled_from("under the mit license apache version 2 cc by nc x".split()), max_size=60))
def test_base_places_match_a_naive_search(words):
    scanner = licenses.LicenseScanner()
    places, _ = scanner.scan([w.encode() for w in words])
    want = []
    for k, phrase in enumerate(licenses.BASE):
        p = phrase.split()
        want += [(k, i) for i in range(len(words)) if words[i : i + len(p)] == p]
    assert sorted(places) == sorted(want)


def test_a_changed_licence_is_one_chain():
    text = "intro words " + licenses.TEMPLATES["mit-text"].replace("free of charge", "at no cost") + " end"
    _, spans = licenses.LicenseScanner().scan(licenses.words_of(text.encode()))
    assert [s.label for s in spans] == ["mit-text"]
    assert spans[0].covered > 0.9 and spans[0].first == 2


def brute_spans(scanner, templates, words):
    """Per template: all maximal matches by comparing every pair of places, groups by gap, and the longest
    common rising chain of their words by the quadratic recurrence."""
    spans = []
    for label, text in templates.items():
        t = text.split()
        need = min(licenses.MIN_MATCH, len(t))
        found = []
        for i in range(len(words)):
            for j in range(len(t)):
                if words[i] == t[j] and (i == 0 or j == 0 or words[i - 1] != t[j - 1]):
                    n = 1
                    while i + n < len(words) and j + n < len(t) and words[i + n] == t[j + n]:
                        n += 1
                    if n >= need:
                        found.append((i, j, n))
        found.sort()
        groups, reach = [], -1
        for m in found:
            if not groups or m[0] > reach + licenses.MAX_GAP:
                groups.append([])
            groups[-1].append(m)
            reach = max(reach, m[0] + m[2])
        for group in groups:
            cells = {(i + x, j + x) for i, j, n in group for x in range(n)}
            rows, cols = max(i for i, _ in cells) + 1, len(t)
            best = [[0] * (cols + 1) for _ in range(rows + 1)]
            for i in range(rows):
                for j in range(cols):
                    best[i + 1][j + 1] = max(best[i][j + 1], best[i + 1][j], best[i][j] + 1 if (i, j) in cells else 0)
            if best[rows][cols] / len(t) >= licenses.COVERED:
                spans.append((label, round(best[rows][cols] / len(t), 9)))
    return sorted(spans)


@settings(max_examples=150, deadline=None)
@given(
    st.lists(st.lists(st.sampled_from("a b c d".split()), min_size=1, max_size=9), min_size=1, max_size=4),
    st.lists(st.sampled_from("a b c d e".split()), max_size=40),
    st.integers(0, 6),
)
def test_chains_match_brute_force_over_overlapping_templates(templates, words, gap):
    named = {f"t{i}": " ".join(t) for i, t in enumerate(templates)}
    old, licenses.MAX_GAP = licenses.MAX_GAP, gap
    try:
        scanner = licenses.LicenseScanner({}, named)
        _, spans = scanner.scan([w.encode() for w in words])
        assert sorted((s.label, round(s.covered, 9)) for s in spans) == brute_spans(scanner, named, words)
    finally:
        licenses.MAX_GAP = old


def test_a_template_inside_a_longer_match_is_found():
    scanner = licenses.LicenseScanner({}, {"A": "a b c d e f g h", "B": "x c d e f"})
    _, spans = scanner.scan(b"a b c d e f g h".split())
    assert [(s.label, s.covered, s.first, s.last) for s in spans] == [("A", 1.0, 0, 7), ("B", 0.8, 2, 5)]


def test_a_word_is_covered_once():
    """A phrase that a template has twice covers only half of it; a doubled word in a text costs nothing."""
    scanner = licenses.LicenseScanner({}, {"twice": "a b c d a b c d", "long": "e f g h i j k l"})
    assert [s.label for s in scanner.scan(b"a b c d".split())[1]] == []
    assert [(s.label, s.covered) for s in scanner.scan(b"e f g h h i j k l".split())[1]] == [("long", 1.0)]


def test_odd_rows(odd_docs, no_docs):
    rows = {(r["doc_id"], r["n_words"]): r for r in licenses.scan_licenses(odd_docs).collect()}
    assert licenses.scan_licenses(odd_docs).count() == odd_docs.count()
    assert licenses.scan_licenses(no_docs).count() == 0
    empty = rows[(0, 0)]
    assert (empty["n_base"], empty["first_word"], empty["labels"], empty["score"]) == (0, None, "", 0.0)
    long = next(r for r in rows.values() if r["doc_id"] == 10)
    assert long["n_base"] == 3000 and long["first_word"] == 0 and long["base_labels"] == "mit" and long["score"] == 1.0
    both = next(r for r in rows.values() if r["doc_id"] == 13)
    assert both["base_labels"] == "cc-by-nc,mit" and both["n_base"] == 2
    assert next(r for r in rows.values() if r["doc_id"] == 14)["base_labels"] == "apache-2"
