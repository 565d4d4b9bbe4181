"""Web archives: legacy ARC files, their conversion to WARC, and reading WARC back.

ARC records are parsed by the field list of their file's version and by their declared lengths;
WARC identifiers, dates, types and digests are synthesised from what they hold. A file's own
description becomes a warcinfo record, and a malformed record is skipped and counted."""

from __future__ import annotations

import hashlib
import io
import re
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import discard, spread_join, utf8, written

# The URL-record fields of both ARC versions.
FIELDS = {
    1: ("URL", "IP-address", "Archive-date", "Content-type", "Archive-length"),
    2: (
        "URL", "IP-address", "Archive-date", "Content-type", "Result-code", "Checksum", "Location", "Offset",
        "Filename", "Archive-length",
    ),
}
#: Equal payloads of this many bytes or more are stored once.
LEAST_SHARED = 100
#: Bytes of compressed members in one archive, zlib's level, and bytes inflated at once.
ARCHIVE_BYTES, LEVEL, STEP = 4 << 20, 1, 1 << 14
#: Bits, at most, of a filter that tells which payloads may have to move (8 MB).
FILTER_BITS = 1 << 26
SOFTWARE = "rowloom"
_UNSAFE = re.compile(r"[\x00-\x20\x7f]")
_SPACE = uuid.UUID("6f1d8a52-6a0b-5d0c-9a53-0d6b7f2b7f10")


@dataclass
class ArcRecord:
    """A record; the last three fields are of version 2 only ("-": none)."""

    url: str
    ip: str
    date: str
    content_type: str
    block: bytes
    result_code: str = "-"
    checksum: str = "-"
    location: str = "-"


def safe_url(url: str | None, page_id: int | None) -> str:
    """A URL without white space or controls; a missing one is named after the page."""
    if not url:
        return f"urn:page:{'' if page_id is None else page_id}"
    return _UNSAFE.sub(lambda m: f"%{ord(m[0]):02X}", url)


def arc_file(records: list[ArcRecord], version: int, name: str = "pages.arc", date: str = "20240101000000") -> bytes:
    """An uncompressed ARC file of version 1 or 2."""
    out = io.BytesIO()

    def put(r: ArcRecord) -> None:
        values = {
            "URL": r.url, "IP-address": r.ip, "Archive-date": r.date, "Content-type": r.content_type, "Result-code": r.result_code,
            "Checksum": r.checksum, "Location": r.location, "Offset": str(out.tell()), "Filename": name,
            "Archive-length": str(len(r.block)),
        }
        out.write(" ".join(values[f] for f in FIELDS[version]).encode() + b"\n" + r.block + b"\n")

    about = f"{version} 0 {SOFTWARE}\n{' '.join(FIELDS[version])}\n".encode()
    put(ArcRecord(f"filedesc://{name}", "0.0.0.0", date, "text/plain", about))
    for r in records:
        put(r)
    return out.getvalue()


def _record(data: bytes, at: int, version: int | None, strict_end: bool) -> tuple[int, ArcRecord, int]:
    """Version, record and the byte after it. Raises ValueError where a header line or a length does not hold."""
    end = data.find(b"\n", at)
    if end < 0:
        raise ValueError(f"unended header line at byte {at}")
    line = data[at:end].decode("utf-8", "replace").rstrip("\r").split(" ")
    start = end + 1
    if version is None:
        if not line[0].startswith("filedesc:") or not line[-1].isdigit():
            raise ValueError(f"no ARC file starts at byte {at}")
        mark = data[start : start + 2]
        version = int(mark[:1]) if mark[1:] == b" " and mark[:1].isdigit() else 0
        if version not in FIELDS:
            raise ValueError("not an ARC file of version 1 or 2")
        if len(line) != len(FIELDS[version]):
            line = [*line[:4], *["-"] * (len(FIELDS[version]) - 5), line[-1]][: len(FIELDS[version])]
    if len(line) != len(FIELDS[version]):
        raise ValueError(f"{len(line)} fields at byte {at}; version {version} has {len(FIELDS[version])}")
    fields = dict(zip(FIELDS[version], line, strict=True))
    date, length = fields["Archive-date"], fields["Archive-length"]
    if not (date.isdigit() and 8 <= len(date) <= 14):
        raise ValueError(f"date {date!r} at byte {at}")
    if not length.isdigit() or start + int(length) > len(data):
        raise ValueError(f"declared length {length} at byte {at} passes the end")
    stop = start + int(length)
    if strict_end and data[stop : stop + 1] not in (b"", b"\n"):
        raise ValueError(f"the record at byte {at} does not end where it says")
    own = [fields.get(f, "-") for f in ("Result-code", "Checksum", "Location")]
    return version, ArcRecord(fields["URL"], fields["IP-address"], date, fields["Content-type"], data[start:stop], *own), stop


def parse_arc(data: bytes, faults: list[tuple[int, str]] | None = None) -> Iterator[ArcRecord]:
    """The records of an ARC file, its own description (a `filedesc:` URL) first.

    Raises ValueError where a header line or a length does not hold; with a list of `faults`, puts
    (byte, reason) there instead and goes on at the next line that starts a record which ends where
    it says, so that one fault costs its record only."""
    at, version, lost = 0, None, False
    while at < len(data):
        if data[at] in b"\r\n":
            at += 1
            continue
        try:
            version, record, at = _record(data, at, version, lost)
        except ValueError as reason:
            if faults is None:
                raise
            if not lost:
                faults.append((at, str(reason)))
            lost = True
            after = data.find(b"\n", at)
            at = len(data) if after < 0 else after + 1
            continue
        lost = False
        yield record


def http_block(payload: bytes) -> bytes:
    return b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload


def warc_date(date: str) -> str:
    """An ARC date of 8 to 14 digits as an ISO instant."""
    d = date.ljust(14, "0")
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def record_id(url: str, date: str, digest: str, source: int | None) -> str:
    """The same record gets the same identifier whenever it is converted."""
    return f"<urn:uuid:{uuid.uuid5(_SPACE, f'{url} {date} {digest} {source}')}>"


def _member(headers: list[tuple[str, str]], block: bytes) -> bytes:
    head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in headers) + f"Content-Length: {len(block)}\r\n\r\n"
    packer = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return packer.compress(head.encode() + block + b"\r\n\r\n") + packer.flush()


def _common(kind: str, url: str, date: str, digest: str, payload_bytes: int, source: int | None) -> list[tuple[str, str]]:
    return [
        ("WARC-Type", kind),
        ("WARC-Record-ID", record_id(url, date, digest, source)),
        ("WARC-Date", warc_date(date)),
        ("WARC-Target-URI", url),
        ("WARC-Payload-Digest", f"sha256:{digest}"),
        ("X-Payload-Length", str(payload_bytes)),
        *([("X-Source-Row", str(source))] if source is not None else []),
    ]


def info_member(about: ArcRecord) -> tuple[str, bytes]:
    """Identifier and gzip member of the warcinfo record that a file's own description becomes."""
    name = about.url.partition("://")[2]
    own = record_id(about.url, about.date, hashlib.sha256(about.block).hexdigest(), None)
    lines = about.block.decode("utf-8", "replace").splitlines()
    fields = {"software": SOFTWARE, "format": "WARC File Format 1.1", "description": "converted from ARC: " + " / ".join(lines)}
    block = "".join(f"{k}: {v}\r\n" for k, v in fields.items()).encode()
    headers = [
        ("WARC-Type", "warcinfo"), ("WARC-Record-ID", own), ("WARC-Date", warc_date(about.date)),
        *([("WARC-Filename", name)] if name else []), ("Content-Type", "application/warc-fields"),
    ]
    return own, _member(headers, block)


def converted_member(record: ArcRecord, source: int | None = None, info: str | None = None) -> tuple[str, int, bytes]:
    """Payload digest, payload length and the gzip member of a converted record.

    A block with an HTTP status line is a response; any other, such as a DNS answer, is a resource
    of the record's own content type."""
    payload, kind, content = record.block, "resource", record.content_type
    if record.block.startswith(b"HTTP/"):
        kind, content = "response", "application/http; msgtype=response"
        head, found, rest = record.block.partition(b"\r\n\r\n")
        payload = rest if found else b""
    digest = hashlib.sha256(payload).hexdigest()
    headers = _common(kind, record.url, record.date, digest, len(payload), source)
    headers += [("Content-Type", content), ("WARC-IP-Address", record.ip)]
    headers += [("WARC-Warcinfo-ID", info)] if info else []
    legacy = (("Result-Code", record.result_code), ("Checksum", record.checksum), ("Location", record.location))
    headers += [(f"X-ARC-{k}", v) for k, v in legacy if v != "-"]
    return digest, len(payload), _member(headers, record.block)


def revisit_member(url: str, date: str, digest: str, payload_bytes: int, source: int | None, first: int) -> bytes:
    headers = _common("revisit", url, date, digest, payload_bytes, source)
    headers += [
        ("Content-Type", "application/http; msgtype=response"),
        ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"),
        ("X-Refers-To-Row", str(first)),
    ]
    return _member(headers, b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n")


def inflate(data: bytes) -> bytes:
    """The bytes of all gzip members; input goes in by small steps, so that no member costs the whole rest."""
    out, at, view = [], 0, memoryview(data)
    while at < len(data):
        unpacker = zlib.decompressobj(31)
        while not unpacker.eof:
            part = view[at : at + STEP]
            if not part:
                raise ValueError("a gzip member is cut off")
            out.append(unpacker.decompress(part))
            at += len(part)
        at -= len(unpacker.unused_data)
    return b"".join(out)


def read_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of every record of a (compressed or plain) WARC file."""
    if data[:2] == b"\x1f\x8b":
        data = inflate(data)
    at = 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        headers = dict(x.split(": ", 1) for x in lines[1:])
        start = end + 4
        stop = start + int(headers["Content-Length"])
        yield headers, data[start:stop]
        at = stop + 4


def convert_file(data: bytes, sources: list[int | None] | None = None) -> tuple[list[bytes], list[tuple[int, str]]]:
    """WARC members of an ARC file (compressed or plain), and its faults. `sources` names the records' rows in order."""
    if data[:2] == b"\x1f\x8b":
        data = inflate(data)
    faults: list[tuple[int, str]] = []
    members, info, at = [], None, 0
    for record in parse_arc(data, faults):
        if record.url.startswith("filedesc:"):
            info, member = info_member(record)
        else:
            member = converted_member(record, sources[at] if sources else None, info)[2]
            at += 1
        members.append(member)
    return members, faults


def convert_archives(files: DataFrame, name_col: str = "name", data_col: str = "data") -> DataFrame:
    """(name, records, faults, data) for each legacy ARC file: its gzip WARC file, the records in it (the
    warcinfo one too) and how many malformed records were skipped. A null or empty file has none of them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, cell in zip(batch.column(0), batch.column(1), strict=True):
                members, faults = convert_file(cell.as_py() or b"")
                columns = [pa.array([name.as_py()], pa.string()), pa.array([len(members)], pa.int64()), pa.array([len(faults)], pa.int64()), pa.array([b"".join(members)], pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, names=["name", "records", "faults", "data"])

    return files.select(F.col(name_col).cast("string").alias("name"), F.col(data_col).cast("binary").alias("data")).mapInArrow(
        run, "name string, records long, faults long, data binary"
    )


def _convert(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pages through ARC files of both versions to WARC members."""
    for batch in batches:
        for k, part in enumerate(batch.slice(i, 64) for i in range(0, batch.num_rows, 64)):
            ids, urls, dates, ips, bodies = (c.to_pylist() for c in part.columns)
            legacy = [
                ArcRecord(safe_url(u, i), ip, date, "text/html", http_block(b), *(("200", "-", "-") if k % 2 else ()))
                for i, u, date, ip, b in zip(ids, urls, dates, ips, bodies, strict=True)
            ]
            members, faults = convert_file(arc_file(legacy, 1 + k % 2, date=max(dates)), ids)
            if faults or len(members) != len(ids) + 1:
                raise ValueError(f"pages did not come through an ARC file: {faults}")
            yield pa.RecordBatch.from_arrays([pa.array(members, pa.binary())], names=["member"])


def _revisits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = zip(*(c.to_pylist() for c in batch.columns), strict=True)
        members = [revisit_member(safe_url(url, page), date, digest.hex(), n, page, first) for page, url, date, digest, n, first in rows]
        yield pa.RecordBatch.from_arrays([pa.array(members, pa.binary())], names=["member"])


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Members packed to archives."""

    def archive(members: list[bytes]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([len(members)], pa.int64()), pa.array([b"".join(members)], pa.binary())], names=["records", "data"])

    held: list[bytes] = []
    size = 0
    for batch in batches:
        for cell in batch.column(0):
            held.append(cell.as_py())
            size += len(held[-1])
            if size >= ARCHIVE_BYTES:
                yield archive(held)
                held, size = [], 0
    if held:
        yield archive(held)


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for cell in batch.column(0):
            rows = []
            for h, block in read_warc(cell.as_py()):
                kind, digest, n = h["WARC-Type"], h.get("WARC-Payload-Digest"), int(h.get("X-Payload-Length", len(block)))
                digest = digest and digest.removeprefix("sha256:")
                if kind in ("response", "resource"):
                    payload = block.partition(b"\r\n\r\n")[2] if kind == "response" else block
                    if len(payload) != n or hashlib.sha256(payload).hexdigest() != digest:
                        raise ValueError(f"payload of {h['WARC-Record-ID']} does not have its digest")
                source, first = h.get("X-Source-Row"), h.get("X-Refers-To-Row")
                rows.append(
                    (
                        None if source is None else int(source), n, digest, kind,
                        None if first is None else int(first), h["WARC-Record-ID"], h["WARC-Date"], h.get("WARC-Target-URI"),
                    )
                )
            types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string()]
            names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "record_id", "warc_date", "target_uri"]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)


def _spots(key: Column, bits: int) -> list[Column]:
    """Two bits of a filter for a 64-bit key."""
    return [F.pmod(key, F.lit(bits)), F.pmod(F.xxhash64(key, F.lit(1)), F.lit(bits))]


def key_filter(keys: DataFrame, n: int) -> tuple[np.ndarray, int]:
    """A Bloom filter of a table of n 64-bit `key`s: 16 bits a key, FILTER_BITS at most. Words of it are or-ed by the tasks."""
    bits = min(FILTER_BITS, max(1 << 12, 1 << (16 * max(1, n) - 1).bit_length()))
    spots = keys.select(F.explode(F.array(*_spots(F.col("key"), bits))).alias("spot"))
    words = spots.groupBy(F.shiftright("spot", 6).alias("at")).agg(F.expr("bit_or(shiftleft(1L, cast(spot % 64 as int)))").alias("word")).toPandas()
    out = np.zeros(bits // 64, "int64")
    out[words["at"].to_numpy("int64")] = words["word"].to_numpy("int64")
    return out, bits


def _maybe(df: DataFrame, table: tuple[np.ndarray, int]) -> Column:
    """Whether a row's `key` may be in the filter (no key: false)."""
    words, bits = df.sparkSession.sparkContext.broadcast(table[0]), table[1]

    @F.pandas_udf("boolean")
    def has(a: pd.Series, b: pd.Series) -> pd.Series:
        known = words.value
        seen = np.ones(len(a), bool)
        for x in (a, b):
            at = x.fillna(0).to_numpy("int64")
            seen &= (known[at >> 6] >> (at & 63)) & 1 == 1
        return pd.Series(seen & a.notna().to_numpy())

    return has(*_spots(F.col("key"), bits))


def write_archives(
    pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html",
    date_col: str | None = None, ip_col: str | None = None,
) -> DataFrame:
    """A written table of archives (records bigint, data binary: a gzip WARC file of some MB each).

    The html of a row is its payload (null: empty). Of rows with equal payloads of 100 bytes or
    more, those with the smallest id are responses and the others revisit it; rows that repeat the
    smallest id are all responses, and a row without an id revisits one that has an id. Without
    columns for them (null: likewise), capture dates follow the id from 2024 on and addresses the URL.

    Revisits are found on digests alone; rows that a filter of them clears are packed where they
    are read, and only the few others, cleared by a join, are shuffled with their payload."""
    page, html = F.col(id_col).cast("long"), utf8(html_col)
    date = F.date_format(F.expr(f"timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(0, 0, 0, pmod(coalesce(cast(`{id_col}` as bigint), 0), 100000000))"), "yyyyMMddHHmmss")
    spot = F.crc32(utf8(url_col))
    ip = F.concat_ws(".", F.lit("10"), *[F.shiftright(spot, k).bitwiseAND(F.lit(255)).cast("string") for k in (16, 8, 0)])
    own = pages.select(
        page.alias("page_id"), F.col(url_col).cast("string").alias("url"),
        (F.coalesce(F.col(date_col).cast("string"), date) if date_col else date).alias("date"),
        (F.coalesce(F.col(ip_col).cast("string"), ip) if ip_col else ip).alias("ip"), html.alias("html"),
    )
    digest = F.when(F.length("html") >= LEAST_SHARED, F.unhex(F.sha2("html", 256)))
    own = own.withColumn("digest", digest).withColumn("key", F.when(F.col("digest").isNotNull(), F.xxhash64(F.coalesce("page_id", F.lit(-1)), "digest")))
    narrow = written(own.where("digest is not null").select("page_id", "url", "date", "digest", "key", F.length("html").cast("long").alias("n")), "digests")
    first = written(
        narrow.groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count("*").alias("copies")).where("copies > 1 and first_id is not null"), "firsts"
    )
    again = written(spread_join(narrow, first, ["digest"], "copies", narrow.count()).where("page_id is null or page_id <> first_id"), "revisits")
    count = again.count()
    cols = ["page_id", "url", "date", "ip", "html"]
    if not count:
        members = own.select(cols).mapInArrow(_convert, "member binary")
    else:
        revisits = _maybe(own, key_filter(again.select("key"), count))
        # rows that the filter holds back wrongly, found without payloads, in a filter of their own
        wrong = written(narrow.where(revisits).join(again.select("key", "digest"), ["key", "digest"], "left_anti").select("key"), "held")
        held = wrong.count()
        members = own.where(~revisits).select(cols).mapInArrow(_convert, "member binary")
        if held:
            back = own.where(revisits & _maybe(own, key_filter(wrong, held)))
            cleared = back.join(again.select("key", "digest"), ["key", "digest"], "left_anti")
            members = members.union(cleared.select(cols).mapInArrow(_convert, "member binary"))
        members = members.union(again.select("page_id", "url", "date", "digest", "n", "first_id").mapInArrow(_revisits, "member binary"))
    out = written(members.mapInArrow(_pack, "records long, data binary"), "archives")
    discard(narrow, first, again)
    return out


def read_archives(archives: DataFrame, data_col: str = "data") -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to, record_id, warc_date, target_uri of
    every record; a warcinfo record has neither page nor digest."""
    return archives.select(data_col).mapInArrow(
        _read,
        "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, "
        "record_id string, warc_date string, target_uri string",
    )
