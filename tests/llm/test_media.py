from __future__ import annotations

import hashlib
import wave
import zlib

import numpy as np
import pytest

from rowloom.llm import media


def test_payload_is_kept(odd_docs, no_docs):
    rows = media.media_columns(odd_docs, keep_media=True).collect()
    assert len(rows) == odd_docs.count()
    texts = {}
    for r in odd_docs.collect():
        texts.setdefault(r["doc_id"], set()).add((r["text"] or "").encode())
    for r in rows:
        data = next(t for t in texts[r["doc_id"]] if len(t) == r["n_bytes"])
        payload = data + bytes(r["payload_bytes"] - len(data))
        assert r["payload_bytes"] % 64 == 0 and 0 <= r["payload_bytes"] - max(1, len(data)) < 64
        assert r["payload_sha256"] == hashlib.sha256(payload).hexdigest()
        assert r["tail_crc32"] == zlib.crc32(payload[-64:])
        assert media.from_wav(bytes(r["media"])) == payload
        assert r["media_sha256"] == hashlib.sha256(bytes(r["media"])).hexdigest() and r["media_bytes"] == len(r["media"])
    equal = {}
    for r in rows:
        equal.setdefault(r["payload_sha256"], set()).add((r["feature"], tuple(r["fingerprint"])))
    assert all(len(x) == 1 for x in equal.values())
    assert media.media_columns(no_docs).count() == 0


def test_peaks_do_not_depend_on_blocks(monkeypatch):
    samples = np.random.default_rng(3).integers(0, 256, 40_000).astype("u1")
    whole = media.peaks(samples)
    monkeypatch.setattr(media, "BLOCK", 7)
    again = media.peaks(samples)
    assert all((a == b).all() for a, b in zip(whole, again, strict=True))


def test_pairs_match_brute_force():
    t, f = np.array([0, 0, 1, 1, 3, 9, 10]), np.array([3, 20, 4, 60, 5, 6, 7])
    want = []
    for i in range(len(t)):
        later = [j for j in range(len(t)) if t[j] > t[i]][: media.FAN]
        want += [(int(t[i]) << 20) | (int(f[i]) << 12) | (int(f[j]) << 4) | int(t[j] - t[i]) for j in later if t[j] - t[i] <= media.REACH]
    assert media.pair_codes(t, f).tolist() == sorted(want)


def test_a_tone_has_its_bin():
    n = np.arange(8000)
    tone = (128 + 100 * np.sin(2 * np.pi * 20 * n / media.WINDOW)).astype("u1")
    _, bins = media.peaks(tone)
    assert (bins == 20).mean() > 0.8


def test_other_formats_are_refused():
    import io

    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(2)
        w.setsampwidth(2)
        w.setframerate(8000)
        w.writeframes(b"abcd")
    with pytest.raises(wave.Error):
        media.from_wav(out.getvalue())
