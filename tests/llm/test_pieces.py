from __future__ import annotations

import hashlib

import numpy as np
import pytest
import sentencepiece
from hypothesis import given, settings
from hypothesis import strategies as st

from rowloom.llm import pieces


@pytest.fixture(scope="module")
def codec(model_path):
    return pieces.PieceCodec(open(model_path, "rb").read())


def library_spans(codec, text):
    """Begin and end, in UTF-8 bytes, of the library's pieces."""
    return [(p.begin, p.end) for p in codec.library.encode(text, return_type="proto").pieces]


def test_ids_and_spans_match_the_library(codec, documents):
    texts = [r["text"] or "" for r in documents.select("text").collect()]
    texts += ["", " ", "  a  b ", "a▁b ▁ c", "\n\n x", "é\0b", "日本語 emoji 😀  ", "z" * 4000, "Ünïcödé  ▁▁ 😀😀 ą", "▁", " é"]
    for text in texts:
        e = codec.encode(text.encode())
        assert e.ids.tolist() == codec.library.encode(text)
        assert e.id_text == ",".join(map(str, e.ids.tolist()))
        got = list(zip(e.begins.tolist(), e.ends.tolist(), strict=True))
        if "\0" not in text:
            assert got == library_spans(codec, text), text
        if len(got):
            assert got[0][0] == 0 and got[-1][1] == len(text.encode())
            assert all(a[1] == b[0] for a, b in zip(got, got[1:], strict=False))


def folding_map():
    rules = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc")
    if not hasattr(rules, "serialized_model_proto"):
        pytest.skip("this library does not show its compiled map")
    from sentencepiece import sentencepiece_model_pb2 as pb

    proto = pb.ModelProto()
    proto.ParseFromString(rules.serialized_model_proto())
    return pieces.CharacterMap(proto.normalizer_spec.precompiled_charsmap)


@pytest.mark.parametrize("table", ["empty", "folding"])
def test_whole_text_walk_is_the_walk_by_characters(table):
    own = object.__new__(pieces.PieceCodec)
    own.map = pieces.CharacterMap(b"") if table == "empty" else folding_map()
    own.squeeze = False

    @settings(max_examples=300, deadline=None)
    @given(st.text(alphabet=st.one_of(st.characters(exclude_categories=["Cs"]), st.sampled_from(" ▁aｆﬁ①½㌔éｶﾞe\u0301\u3000")), max_size=50), st.booleans())
    def same(text, dummy):
        own.dummy = dummy
        assert own.sources(text.encode()).tolist() == own.normalise(text.encode())[1]

    same()
    data = np.frombuffer("ｆｏｏ ﬁne ① plain e\u0301".encode(), "u1")
    starts = np.arange(len(data))
    lengths, targets = own.map.longest_all(data, starts)
    for i in starts.tolist():
        n, new = own.map.longest(data.tobytes(), i)
        assert lengths[i] == n and (not n or own.map.target(int(targets[i])) == new)


@settings(max_examples=60, deadline=None)
@given(st.text(max_size=60))
def test_any_text_round_trips(text):
    from rowloom.llm.queries import tokenizer_path

    own = pieces.codec(open(tokenizer_path(), "rb").read())
    e = own.encode(text.encode("utf-8", "replace"))
    clean = text.encode("utf-8", "replace").decode()
    assert own.decode(e.ids.tolist()) == clean.replace("▁", " ")


def test_longest_prefix_normalisation_matches_the_library():
    own = object.__new__(pieces.PieceCodec)
    own.map = folding_map()
    own.dummy, own.squeeze = False, False
    for text in ("ｆｏｏ ① Ａ", "ﬁne  ﬂow", "étude", "plain", "㌔㍍ ½", "日本"):
        raw, source = own.normalise(text.encode())
        direct = "".join(_mapped(own.map, text.encode()))
        assert raw.decode().replace("▁", " ") == direct
        assert len(source) == len(raw) + 1 and source == sorted(source) and source[-1] == len(text.encode())
        loose = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc")
        assert direct.strip() == loose.normalize(text).replace("▁", " ").strip() or "  " in text


def _mapped(table, data):
    at = 0
    while at < len(data):
        n, target = table.longest(data, at)
        if not n:
            n = pieces._char_length(data[at])
            target = data[at : at + n]
        yield target.decode()
        at += n


def test_odd_rows(spark, odd_docs, no_docs, model_path, codec):
    got = pieces.encode_documents(odd_docs, model_path).collect()
    want = odd_docs.collect()
    assert len(got) == len(want)
    by = {(r["doc_id"], r["ids_sha256"]) for r in got}
    for r in want:
        ids = codec.library.encode(r["text"] or "")
        assert (r["doc_id"], hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()) in by
    assert pieces.encode_documents(no_docs, model_path).count() == 0
    back = pieces.decode_documents(pieces.encode_documents(odd_docs, model_path), model_path)
    assert all(hashlib.sha256(r["decoded"].encode()).hexdigest() == r["decoded_sha256"] for r in back.collect())
