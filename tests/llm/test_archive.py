from __future__ import annotations

import hashlib
from dataclasses import replace

import pytest

from rowloom.llm import archive


def brute(rows):
    first = {}
    for page, html in rows:
        data = (html or "").encode()
        if len(data) >= 100 and page is not None:
            first[data] = min(first.get(data, page), page)
    out = []
    for page, html in rows:
        data = (html or "").encode()
        head = first.get(data)
        revisit = head is not None and head != page
        out.append((page, len(data), hashlib.sha256(data).hexdigest(), "revisit" if revisit else "response", head if revisit else None))
    return sorted(out, key=str)


def test_odd_pages(spark):
    big, other = "<p>" + "é" * 60, "x" * 100
    rows = [(3, "http://a b/\n", big), (1, None, big), (2, "", None), (2, "u", None), (7, "u", other), (5, "u", other), (5, "u", other), (None, "u", big), (8, "u", "y" * 99), (9, "u", "y" * 99), (4, "http://z", "l" * 300_000)]
    pages = spark.createDataFrame([(*r, 1) for r in rows], "page_id long, url string, html string, digest int")
    back = archive.read_archives(archive.write_archives(pages)).collect()
    got = [r for r in back if r["record_type"] != "warcinfo"]
    assert any(r["record_type"] == "warcinfo" and r["page_id"] is None and r["payload_digest"] is None for r in back)
    assert sorted([tuple(r)[:5] for r in got], key=str) == brute([(a, c) for a, _, c in rows])
    assert len({r["record_id"] for r in got if r["page_id"] not in (2, 5)}) == len([r for r in got if r["page_id"] not in (2, 5)])
    assert {r["warc_date"] for r in got if r["page_id"] == 7} == {"2024-01-01T00:00:07Z"}
    assert archive.read_archives(archive.write_archives(pages.where("false"))).count() == 0


def test_a_large_group_of_nulls_and_a_full_filter(spark, monkeypatch):
    """Rows without an id that share one payload, many copies of others, and a filter so small that it clears nobody."""
    rows = [(None, "u", "n" * 120)] * 500 + [(4, "u", "n" * 120)]
    rows += [(10 + i, f"u{i}", "abc"[i % 3] * 150 if i % 2 else f"page {i} " * 20) for i in range(600)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    want = brute([(a, c) for a, _, c in rows])
    for bits in (1 << 26, 64):
        monkeypatch.setattr(archive, "FILTER_BITS", bits)
        got = archive.read_archives(archive.write_archives(pages)).where("record_type <> 'warcinfo'").collect()
        assert sorted([tuple(r)[:5] for r in got], key=str) == want


def test_given_dates_and_addresses(spark):
    pages = spark.createDataFrame([(1, "u", "x", "20010203040506", "1.2.3.4"), (2, "u", "y", None, None)], "page_id long, url string, html string, d string, ip string")
    archives = archive.write_archives(pages, date_col="d", ip_col="ip")
    heads = {h["X-Source-Row"]: h for r in archives.collect() for h, _ in archive.read_warc(bytes(r["data"])) if h["WARC-Type"] == "response"}
    assert (heads["1"]["WARC-Date"], heads["1"]["WARC-IP-Address"]) == ("2001-02-03T04:05:06Z", "1.2.3.4")
    assert heads["2"]["WARC-Date"] == "2024-01-01T00:00:02Z" and heads["2"]["WARC-IP-Address"].startswith("10.")


RECORDS = [
    archive.ArcRecord("http://a/", "1.2.3.4", "20010203040506", "text/html", archive.http_block(b"hello\n\nthere")),
    archive.ArcRecord("http://b/", "0.0.0.0", "20010203040507", "text/plain", b""),
    archive.ArcRecord("dns:a", "0.0.0.0", "20010203", "text/dns", b"a 1.2.3.4\n"),
]


@pytest.mark.parametrize("version", [1, 2])
def test_arc_versions(version):
    records = list(RECORDS)
    if version == 2:
        records[0] = replace(records[0], result_code="302", checksum="abc", location="http://c/")
    data = archive.arc_file(records, version)
    about, *back = archive.parse_arc(data)
    assert back == records and about.url == "filedesc://pages.arc"
    with pytest.raises(ValueError):
        list(archive.parse_arc(data[:-10]))
    for bad in (b"not an archive 5\nabcde\n", b"filedesc://x 0.0.0.0 20010203 text/plain 9\n7 0 other\n"):
        with pytest.raises(ValueError):
            list(archive.parse_arc(bad))


@pytest.mark.parametrize("version", [1, 2])
def test_malformed_records_are_skipped_and_counted(spark, version):
    data = archive.arc_file(RECORDS, version)
    line, first = data.index(b"http://b/"), data.index(b"\n", data.index(b"http://a/"))
    broken = {
        "length": data[:first] + b"99999" + data[first:],
        "fields": data[:line] + b"one two three\nfour\n" + data[line:],
        "date": data.replace(b"20010203040507", b"2001-02-03 ...", 1) if version == 1 else data.replace(b"20010203040507", b"2001:02:03:...", 1),
        "end": data + b"http://z/ 0.0.0.0 20010203 text/html 7",
    }
    kept = {"length": ["http://b/", "dns:a"], "fields": ["http://a/", "http://b/", "dns:a"], "date": ["http://a/", "dns:a"], "end": ["http://a/", "http://b/", "dns:a"]}
    for name, bytes_ in broken.items():
        faults = []
        assert [r.url for r in archive.parse_arc(bytes_, faults)][1:] == kept[name], name
        assert len(faults) == 1, name
        with pytest.raises(ValueError):
            list(archive.parse_arc(bytes_))
    files = spark.createDataFrame([*((k, bytearray(v)) for k, v in broken.items()), ("none", None), ("junk", bytearray(b"junk\nmore"))], "name string, data binary")
    got = {r["name"]: r for r in archive.convert_archives(files).collect()}
    assert {k: (r["records"], r["faults"]) for k, r in got.items()} == {**{k: (len(v) + 1, 1) for k, v in kept.items()}, "none": (0, 0), "junk": (0, 1)}


def test_conversion_synthesises_headers():
    block = archive.http_block(b"payload")
    record = archive.ArcRecord("http://a/", "1.2.3.4", "20010203040506", "text/html", block, "200", "abc", "-")
    digest, n, member = archive.converted_member(record, 9, "<urn:uuid:x>")
    ((headers, got),) = archive.read_warc(member)
    assert got == block and n == 7 and digest == hashlib.sha256(b"payload").hexdigest()
    assert headers["WARC-Date"] == "2001-02-03T04:05:06Z" and headers["WARC-Type"] == "response"
    assert headers["WARC-Record-ID"] == archive.record_id("http://a/", "20010203040506", digest, 9)
    assert (headers["X-ARC-Result-Code"], headers["X-ARC-Checksum"], headers["WARC-Warcinfo-ID"]) == ("200", "abc", "<urn:uuid:x>")
    assert "X-ARC-Location" not in headers
    members, faults = archive.convert_file(archive.arc_file(RECORDS, 1))
    heads = [h for h, _ in archive.read_warc(b"".join(members))]
    assert [h["WARC-Type"] for h in heads] == ["warcinfo", "response", "resource", "resource"] and not faults
    assert heads[0]["WARC-Filename"] == "pages.arc" and heads[1]["WARC-Warcinfo-ID"] == heads[0]["WARC-Record-ID"]
    assert heads[3]["Content-Type"] == "text/dns" and heads[3]["WARC-Date"] == "2001-02-03T00:00:00Z"
