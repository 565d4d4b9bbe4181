"""SentencePiece encoding with original byte spans, and decoding.

A text is normalised by longest-prefix replacement through the model's compiled character map,
with the source offset of every normalised byte kept; the normalised text is segmented by the
model, and each piece is projected back to the bytes that it came from."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import accumulate
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import lean, utf8

SPACE = "▁"
_MARK = SPACE.encode()
#: Texts longer than this are rare: batches are cut so that few of them are held at once.
SLICE_ROWS = 256


class CharacterMap:
    """A compiled character map: a double-array trie of source prefixes with offsets of replacements."""

    def __init__(self, blob: bytes):
        size = int.from_bytes(blob[:4], "little")
        self.table = np.frombuffer(blob, "<u4", size // 4, 4 if blob else 0).astype("int64")
        self.units, self.targets = self.table.tolist(), blob[4 + size :]

    def longest(self, data: bytes, at: int) -> tuple[int, bytes]:
        """Length of the longest mapped prefix of `data` at `at`, and its replacement; (0, b"") if none."""
        if not self.units:
            return 0, b""
        units, best, target = self.units, 0, -1
        node = (self.units[0] >> 10) << ((self.units[0] & 512) >> 6)
        for i in range(at, len(data)):
            node ^= data[i]
            if node >= len(units) or (unit := units[node]) & 0x800000FF != data[i]:
                break
            node ^= (unit >> 10) << ((unit & 512) >> 6)
            if unit & 256:
                best, target = i + 1 - at, units[node] & 0x7FFFFFFF
        if not best:
            return 0, b""
        return best, self.target(target)

    def target(self, at: int) -> bytes:
        return self.targets[at : self.targets.index(b"\0", at)]

    def longest_all(self, data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """`longest` from every one of `starts` at once: lengths (0: none) and places of replacements.

        All walks go down the trie together, a byte a step, and those that end drop out."""
        best, target = np.zeros(len(starts), "int64"), np.full(len(starts), -1)
        units = self.table
        if not len(units) or not len(starts):
            return best, target
        walk, at = np.arange(len(starts)), starts.copy()
        node = np.full(len(starts), (units[0] >> 10) << ((units[0] & 512) >> 6))
        while len(walk):
            inside = at < len(data)
            walk, at, node = walk[inside], at[inside], node[inside]
            byte = data[at].astype("int64")
            node = node ^ byte
            known = node < len(units)
            unit = units[np.where(known, node, 0)]
            known &= (unit & 0x800000FF) == byte
            walk, at, node, unit = walk[known], at[known], node[known], unit[known]
            node = node ^ ((unit >> 10) << ((unit & 512) >> 6))
            at = at + 1
            ends = (unit & 256) > 0
            best[walk[ends]] = at[ends] - starts[walk[ends]]
            target[walk[ends]] = units[node[ends]] & 0x7FFFFFFF
        return best, target


def _char_length(lead: int) -> int:
    return 1 if lead < 0x80 else 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4


@dataclass
class Encoding:
    """Ids and, for each, the bytes of the original text that it covers (begin, end)."""

    ids: np.ndarray
    begins: np.ndarray
    ends: np.ndarray
    id_text: str


class PieceCodec:
    """Encoder and decoder of one model, given as its serialised bytes."""

    def __init__(self, model: bytes):
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        proto.ParseFromString(model)
        spec = proto.normalizer_spec
        if proto.trainer_spec.treat_whitespace_as_suffix or not spec.escape_whitespaces:
            raise ValueError("models with space suffixes or unescaped spaces are not supported")
        self.map = CharacterMap(spec.precompiled_charsmap)
        self.dummy, self.squeeze = spec.add_dummy_prefix, spec.remove_extra_whitespaces
        self.library = sentencepiece.SentencePieceProcessor()
        self.library.LoadFromSerializedProto(model)
        kinds = pb.ModelProto.SentencePiece
        self.unknown = {i for i, p in enumerate(proto.pieces) if p.type == kinds.UNKNOWN}
        self.widths = np.array([1 if p.type == kinds.BYTE else len(p.piece.encode()) for p in proto.pieces])
        self.names = [str(i) for i in range(len(proto.pieces))]

    def normalise(self, data: bytes) -> tuple[bytes, list[int]]:
        """Normalised bytes and, for each of them and the end, the offset in `data` of its source."""
        out, source = bytearray(), []
        at, n, after_space = 0, len(data), self.squeeze
        started = not self.dummy
        while at < n:
            length, target = self.map.longest(data, at)
            if not length:
                length = min(_char_length(data[at]), n - at)
                target = data[at : at + length]
            if self.squeeze and after_space:
                target = target.lstrip(b" ")
            if target:
                if not started:
                    out += _MARK
                    source += [at] * 3
                    started = True
                for b in target:
                    got = _MARK if b == 32 else bytes((b,))
                    out += got
                    source += [at] * len(got)
                after_space = target.endswith(b" ")
            at += length
        if self.squeeze:
            while out.endswith(_MARK) and len(out) > 3 * self.dummy:
                del out[-3:]
                n = source[-3]
                del source[-3:]
        source.append(n)
        return bytes(out), source

    def sources(self, data: bytes) -> np.ndarray:
        """The offsets that `normalise` gives, for a whole text at once: the map's longest prefixes at
        all characters, taken from the left, and one source offset for each normalised byte and the end.

        Models that squeeze spaces look back at what was written, and take the walk by characters."""
        if self.squeeze:
            return np.array(self.normalise(data)[1], "int64")
        flat = np.frombuffer(data, "u1")
        starts = np.flatnonzero((flat & 0xC0) != 0x80)
        length, target = self.map.longest_all(flat, starts)
        # each byte as it is, from its character's start; a space is a mark of three bytes
        origin = np.zeros(len(flat), "int64")
        origin[starts] = starts
        origin = np.maximum.accumulate(origin)
        width = np.where(flat == 32, 3, 1)
        inserted: list[tuple[int, int]] = []
        reach = 0
        for k in np.flatnonzero(length).tolist():
            at = int(starts[k])
            if at < reach:
                continue
            reach = at + int(length[k])
            width[at:reach] = 0
            new = self.map.target(int(target[k]))
            inserted.append((at, len(new) + 2 * new.count(b" ")))
        for at, n in inserted:
            width[at] = n
        out = np.repeat(origin, width)
        dummy = [out[:1]] * 3 if self.dummy and len(out) else []
        return np.concatenate([*dummy, out, [len(flat)]])

    def encode(self, data: bytes) -> Encoding:
        """Encodes a whole text given as UTF-8; an empty one has no pieces."""
        try:
            text = data.decode()
        except UnicodeDecodeError:
            text = data.decode(errors="replace")
            data = text.encode()
        ids = self.library.encode(text, num_threads=1)
        if not ids:
            none = np.empty(0, "int32")
            return Encoding(none, none, none, "")
        id_text = ",".join([self.names[i] for i in ids])
        if self.unknown.isdisjoint(ids):
            stops = np.cumsum(self.widths[ids])
        else:
            stops = np.cumsum([len(p.surface.encode()) for p in self.library.encode(text, return_type="proto").pieces])
        ends = self.sources(data)[stops]
        begins = np.concatenate([[0], ends[:-1]])
        return Encoding(np.array(ids, "int32"), begins.astype("int32"), ends.astype("int32"), id_text)

    def decode(self, ids: list[int]) -> str:
        return self.library.decode(ids)


@lru_cache(maxsize=2)
def codec(model: bytes) -> PieceCodec:
    return PieceCodec(model)


def _lists(arrays: list[np.ndarray]) -> pa.ListArray:
    offsets = np.array([0, *accumulate(map(len, arrays))], "int32")
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([np.empty(0, "int32"), *arrays]).astype("int32")))


def encode_documents(
    docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", arrays: bool = True
) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, spans_sha256 and, with `arrays`, ids, begins, ends.

    Spans are offsets in the UTF-8 bytes of the whole text; spans_sha256 covers them as
    little-endian 32-bit begins followed by ends. A null text counts as an empty one, which has no
    pieces; ids may be null or repeat, and every row gives one row. Extra columns are ignored.
    The model is read once, on the driver, and shipped with the tasks (under 1 MB)."""
    model = Path(model_path).read_bytes()
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, spans_sha256 string"
    schema += ", ids array<int>, begins array<int>, ends array<int>" if arrays else ""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(model)
        for batch in batches:
            for part in (batch.slice(i, SLICE_ROWS) for i in range(0, batch.num_rows, SLICE_ROWS)):
                digests, kept = [], []
                for cell in part.column(1):
                    e = own.encode(cell.as_py())
                    digests.append(
                        (
                            len(e.ids),
                            hashlib.sha256(e.id_text.encode()).hexdigest(),
                            hashlib.sha256(own.decode(e.ids.tolist()).encode()).hexdigest(),
                            hashlib.sha256(e.begins.tobytes() + e.ends.tobytes()).hexdigest(),
                        )
                    )
                    if arrays:
                        kept.append(e)
                columns = [part.column(0), *(pa.array(x) for x in zip(*digests, strict=True))]
                if arrays:
                    columns += [_lists([getattr(e, k) for e in kept]) for k in ("ids", "begins", "ends")]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "spans_sha256", "ids", "begins", "ends"]
                yield pa.RecordBatch.from_arrays(columns, names=names[: len(columns)])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text")).mapInArrow(lean(run), schema)


def decode_documents(encoded: DataFrame, model_path: str, ids_col: str = "ids") -> DataFrame:
    """`encoded` with the text that its ids decode to, as column `decoded` (null ids: null)."""
    model = Path(model_path).read_bytes()

    @F.pandas_udf("string")
    def back(ids):  # noqa: ANN001, ANN202 - a pandas Series each way
        own = codec(model)
        return ids.map(lambda x: None if x is None else own.decode([int(i) for i in x]))

    return encoded.withColumn("decoded", back(F.col(ids_col)))


__all__ = ["CharacterMap", "Encoding", "PieceCodec", "decode_documents", "encode_documents"]
