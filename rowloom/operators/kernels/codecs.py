"""Byte codecs of integer code columns: each encoder has a decoder that gives the codes back."""

from __future__ import annotations

import bz2
import struct
import zlib

import numpy as np
import pyarrow as pa

KINDS = ("plain", "rle", "prefix", "sparse", "indirect", "lz4_raw", "snappy", "zstd", "gzip", "bz2")
_STANDARD = {"gzip": (zlib.compress, zlib.decompress), "bz2": (bz2.compress, bz2.decompress)}


def pack_bits(values: np.ndarray, width: int) -> bytes:
    """Values of `width` bits each, most significant bit first."""
    if width == 0 or not len(values):
        return b""
    v = np.asarray(values, "uint64")
    bits = ((v[:, None] >> np.arange(width - 1, -1, -1, dtype="uint64")) & np.uint64(1)).astype("u1")
    return np.packbits(bits.ravel()).tobytes()


def unpack_bits(data: bytes, count: int, width: int) -> np.ndarray:
    if width == 0 or not count:
        return np.zeros(count, "int64")
    bits = np.unpackbits(np.frombuffer(data, "u1"), count=count * width).reshape(count, width)
    return bits.astype("int64") @ (1 << np.arange(width - 1, -1, -1, dtype="int64"))


def _packed_bytes(count: int, width: int) -> int:
    return (count * width + 7) // 8


def _width(x: int) -> int:
    return max(0, x - 1).bit_length()


def encode(codes: np.ndarray, kind: str, card: int, p: int = 128) -> bytes:
    """One column chunk: a header (rows, distinct codes) and the body of the codec."""
    codes = np.asarray(codes, "int64")
    n = len(codes)
    head = struct.pack("<IQ", n, card)
    width = _width(card)
    if kind == "plain":
        return head + pack_bits(codes, width)
    if kind == "rle":
        starts = np.flatnonzero(np.concatenate([[True], codes[1:] != codes[:-1]])) if n else np.empty(0, "int64")
        lengths = np.diff(np.append(starts, n))
        w = _width(n)
        body = pack_bits(codes[starts], width) + pack_bits(starts, w) + pack_bits(lengths - 1, w)
        return head + struct.pack("<I", len(starts)) + body
    if kind in ("lz4_raw", "snappy", "zstd", "gzip", "bz2"):
        raw = codes.astype("<i4").tobytes()
        if kind in _STANDARD:
            return head + _STANDARD[kind][0](raw)
        return head + pa.Codec(kind).compress(raw, asbytes=True)
    blocks = [codes[i : i + p] for i in range(0, n, p)]
    out = [head]
    for b in blocks:
        if kind == "prefix":
            differs = np.flatnonzero(b != b[0])
            first = int(differs[0]) if len(differs) else len(b)
            out.append(struct.pack("<B", first - 1) + pack_bits(np.concatenate([b[:1], b[first:]]), width))
        elif kind == "sparse":
            values, counts = np.unique(b, return_counts=True)
            top = values[counts.argmax()]
            out.append(pack_bits((b == top).astype("int64"), 1) + pack_bits(np.concatenate([[top], b[b != top]]), width))
        elif kind == "indirect":
            values, local = np.unique(b, return_inverse=True)
            out.append(struct.pack("<B", len(values) - 1) + pack_bits(values, width) + pack_bits(local, _width(len(values))))
        else:
            raise ValueError(f"codec is one of {KINDS}")
    return b"".join(out)


def decode(data: bytes, kind: str, p: int = 128) -> np.ndarray:
    n, card = struct.unpack_from("<IQ", data)
    at, width = 12, _width(card)
    if kind == "plain":
        return unpack_bits(data[at:], n, width)
    if kind == "rle":
        (runs,) = struct.unpack_from("<I", data, at)
        at += 4
        w = _width(n)
        values = unpack_bits(data[at : at + _packed_bytes(runs, width)], runs, width)
        at += _packed_bytes(runs, width) + _packed_bytes(runs, w)
        return np.repeat(values, unpack_bits(data[at:], runs, w) + 1) if runs else np.empty(0, "int64")
    if kind in ("lz4_raw", "snappy", "zstd", "gzip", "bz2"):
        raw = _STANDARD[kind][1](data[at:]) if kind in _STANDARD else pa.Codec(kind).decompress(data[at:], 4 * n, asbytes=True)
        return np.frombuffer(raw, "<i4").astype("int64")
    out = []
    for start in range(0, n, p):
        b = min(p, n - start)
        if kind == "prefix":
            first = data[at] + 1
            at += 1
            size = _packed_bytes(1 + b - first, width)
            got = unpack_bits(data[at : at + size], 1 + b - first, width)
            out.append(np.concatenate([np.repeat(got[:1], first), got[1:]]))
        elif kind == "sparse":
            size = _packed_bytes(b, 1)
            mask = unpack_bits(data[at : at + size], b, 1) == 1
            at += size
            others = int(b - mask.sum())
            size = _packed_bytes(1 + others, width)
            got = unpack_bits(data[at : at + size], 1 + others, width)
            block = np.repeat(got[:1], b)
            block[~mask] = got[1:]
            out.append(block)
        elif kind == "indirect":
            own = data[at] + 1
            at += 1
            values = unpack_bits(data[at : at + _packed_bytes(own, width)], own, width)
            at += _packed_bytes(own, width)
            size = _packed_bytes(b, _width(own))
            out.append(values[unpack_bits(data[at : at + size], b, _width(own))])
        else:
            raise ValueError(f"codec is one of {KINDS}")
        at += size
    return np.concatenate(out) if out else np.empty(0, "int64")
