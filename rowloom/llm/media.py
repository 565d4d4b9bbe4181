"""Media columns: texts as 8-bit WAV payloads, short-time Fourier transforms, and fingerprints
of spectral-peak pairs stored as time-coded arrays."""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import utf8

ALIGN, RATE = 64, 8000
#: Samples of a window and between window starts.
WINDOW, HOP = 256, 128
#: Frequency bands (bin ranges) that give one peak for each frame at most.
BANDS = ((2, 12), (12, 40), (40, 129))
#: A peak pairs with later peaks within this many frames, nearest first, up to FAN of them.
REACH, FAN = 6, 3
#: Frames transformed at once, so that memory does not follow the length of a text.
BLOCK = 4096
_TAPER = np.hanning(WINDOW + 1)[:-1].astype("float32")


def padded(data: bytes) -> bytes:
    """`data` and zero bytes up to a positive multiple of 64."""
    return data + bytes(max(ALIGN, -(-len(data) // ALIGN) * ALIGN) - len(data))


def to_wav(payload: bytes) -> bytes:
    """One channel of 8-bit samples, one sample a byte."""
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(RATE)
        w.writeframes(payload)
    return out.getvalue()


def from_wav(media: bytes) -> bytes:
    """The sample bytes; raises wave.Error where the file is not 8-bit mono."""
    with wave.open(io.BytesIO(media), "rb") as w:
        if w.getsampwidth() != 1 or w.getnchannels() != 1:
            raise wave.Error("8-bit mono is expected")
        return w.readframes(w.getnframes())


def spectrogram(samples: np.ndarray, first: int, count: int) -> np.ndarray:
    """Power of `count` frames from frame `first` on; samples after the end are silence."""
    at = first * HOP
    piece = np.full((count - 1) * HOP + WINDOW, 0, "float32")
    got = samples[at : at + len(piece)]
    piece[: len(got)] = got.astype("float32") - 128.0
    frames = np.lib.stride_tricks.sliding_window_view(piece, WINDOW)[::HOP]
    spectrum = np.fft.rfft(frames * _TAPER, axis=1)
    return spectrum.real**2 + spectrum.imag**2


def peaks(samples: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Frame and bin of every spectral peak, by frame and then bin.

    In each band a frame's strongest bin is a peak if it is over the frame's mean power and no
    weaker than the same bin in both neighbouring frames."""
    total = max(1, -(-max(0, len(samples) - WINDOW) // HOP) + 1)
    frames, bins = [], []
    for start in range(0, total, BLOCK):
        lo, hi = max(0, start - 1), min(total, start + BLOCK + 1)
        power = spectrogram(samples, lo, hi - lo)
        skip, take = start - lo, min(BLOCK, total - start)
        own = power[skip : skip + take]
        mean = own.mean(axis=1)
        rows = np.arange(take)
        before, after = np.maximum(rows + skip - 1, 0), np.minimum(rows + skip + 1, len(power) - 1)
        for a, b in BANDS:
            top = own[:, a:b].argmax(axis=1) + a
            value = own[rows, top]
            good = np.flatnonzero((value > mean) & (value >= power[before, top]) & (value >= power[after, top]))
            frames.append(good + start)
            bins.append(top[good])
    t, f = np.concatenate(frames), np.concatenate(bins)
    order = np.lexsort((f, t))
    return t[order], f[order]


def pair_codes(t: np.ndarray, f: np.ndarray) -> np.ndarray:
    """Time-coded pairs: frame << 20 | first bin << 12 | second bin << 4 | frames between."""
    found = []
    for step in range(1, FAN * len(BANDS) + 1):
        if step >= len(t):
            break
        gap = t[step:] - t[:-step]
        # targets are later frames; FAN of the first ones after the anchor's own frame
        rank = step - (np.searchsorted(t, t[:-step], "right") - np.arange(len(t) - step)) + 1
        good = (gap > 0) & (gap <= REACH) & (rank <= FAN)
        found.append((t[:-step][good] << 20) | (f[:-step][good] << 12) | (f[step:][good] << 4) | gap[good])
    return np.sort(np.concatenate(found)) if found else np.empty(0, "int64")


def fingerprint(media: bytes) -> np.ndarray:
    t, f = peaks(np.frombuffer(from_wav(media), "u1"))
    return pair_codes(t.astype("int64"), f.astype("int64"))


def feature_text(codes: np.ndarray) -> str:
    """A short text of a fingerprint: the number of pairs and a 128-bit digest of their codes."""
    return f"{len(codes)}:{xxhash.xxh3_128_hexdigest(codes.astype('<i8').tobytes())}"


def media_columns(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep_media: bool = False
) -> DataFrame:
    """doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature,
    fingerprint array<bigint> and, with `keep_media`, media binary.

    Each whole text is stored as a WAV file of its padded bytes; digests and features come from
    the bytes read back from it. A null or empty text is 64 zero bytes; equal texts give equal
    values; ids may be null or repeat; extra columns are ignored."""
    schema = (
        "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, "
        "media_sha256 string, feature string, fingerprint array<bigint>" + ", media binary" * keep_media
    )
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 256) for i in range(0, batch.num_rows, 256)):
                rows, codes = [], []
                for cell in part.column(1):
                    data = cell.as_py()
                    media = to_wav(padded(data))
                    back = from_wav(media)
                    code = fingerprint(media)
                    codes.append(code)
                    row = (len(data), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-ALIGN:]), len(media))
                    rows.append((*row, hashlib.sha256(media).hexdigest(), feature_text(code), *([media] if keep_media else [])))
                columns = [pa.array(x) for x in zip(*rows, strict=True)]
                offsets = pa.array(np.cumsum([0, *map(len, codes)]).astype("int32"))
                columns.insert(7, pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([np.empty(0, "int64"), *codes]))))
                yield pa.RecordBatch.from_arrays([part.column(0), *columns], names=names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text")).mapInArrow(run, schema)
