"""SentencePiece encoding and decoding that keeps source offsets.

Normalisation walks the text with longest-prefix matches in the model's compiled character map (a
double-array trie) and records for every normalised byte the source byte it comes from; each piece is
then projected to the span of original bytes that it covers.  Segmentation is the library's own.
Where no piece holds a space mark after another character, words are independent, so each distinct
word is encoded, and its ids decoded, once; the normalised lengths of its pieces are summed up along the
text and projected through the text's alignment like those of any other.

Defined cases: a null text is an empty one (only the end id, decoded empty); texts of any length are
encoded whole; repeated rows give repeated rows; further columns are ignored.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import in_pieces, slices

SPACE = "▁"
_MARK = SPACE.encode()
# Fixed values of the model file: piece types.
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
_CODECS: dict[str, PieceCodec] = {}


class CharMap:
    """Longest-prefix lookups in a compiled character map: a trie size, a double-array trie, replacements."""

    def __init__(self, blob: bytes) -> None:
        self.units: tuple[int, ...] = ()
        self.texts = b""
        if blob:
            (size,) = struct.unpack_from("<I", blob)
            self.units = struct.unpack_from(f"<{size // 4}I", blob, 4)
            self.texts = blob[4 + size :]

    def longest(self, data: bytes, at: int) -> tuple[int, bytes] | None:
        """(source bytes matched, replacement), or None."""
        if not self.units:
            return None
        found, unit = None, self.units[0]
        node = (unit >> 10) << ((unit & 0x200) >> 6)
        for i in range(at, len(data)):
            node ^= data[i]
            unit = self.units[node]
            if unit & 0x800000FF != data[i]:
                break
            node ^= (unit >> 10) << ((unit & 0x200) >> 6)
            if unit >> 8 & 1:
                start = self.units[node] & 0x7FFFFFFF
                found = i + 1 - at, self.texts[start : self.texts.index(b"\0", start)]
        return found


class Normalizer:
    def __init__(self, spec) -> None:
        self.map = CharMap(spec.precompiled_charsmap)
        self.prefix, self.squeeze, self.escape = spec.add_dummy_prefix, spec.remove_extra_whitespaces, spec.escape_whitespaces

    @property
    def plain(self) -> bool:
        return not self.map.units and self.prefix and not self.squeeze and self.escape

    def _steps(self, data: bytes) -> Iterator[tuple[bytes, int, int]]:
        """(replacement, source begin, source end) of each match or single character."""
        at = 0
        while at < len(data):
            hit = self.map.longest(data, at)
            if hit:
                n, put = hit
            else:
                lead = data[at]
                n = 1 if lead < 0x80 else 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4
                put = data[at : at + n]
            yield put, at, at + n
            at += n

    def __call__(self, data: bytes) -> tuple[bytes, np.ndarray]:
        """Normalised bytes and the source byte of each (one more entry for the end)."""
        mark = _MARK if self.escape else b" "
        if not self.map.units and not self.squeeze:  # the map matches nowhere: only spaces change
            return self._spaced(data, mark)
        out, source = bytearray(), []
        steps = [*self._steps(data)]
        if self.squeeze:
            while steps and not steps[0][0].strip(b" "):
                steps.pop(0)
        if not steps:
            return b"", np.array([len(data)])
        if self.prefix:
            out += mark
            source += [steps[0][1]] * len(mark)
        spaced = self.squeeze
        for put, begin, _ in steps:
            if self.squeeze and spaced:
                put = put.lstrip(b" ")
            for byte in put:
                piece = mark if byte == 0x20 else bytes([byte])
                out += piece
                source += [begin] * len(piece)
            if put:
                spaced = self.squeeze and put.endswith(b" ")
        end = steps[-1][2]
        while self.squeeze and out.endswith(mark):
            del out[len(out) - len(mark) :]
            end = source[len(out)]
            del source[len(out) :]
        return bytes(out), np.array([*source, end])


    def _spaced(self, data: bytes, mark: bytes) -> tuple[bytes, np.ndarray]:
        if not data:
            return b"", np.zeros(1, np.int64)
        raw = np.frombuffer(data, np.uint8)
        lead = np.maximum.accumulate(np.where(raw & 0xC0 != 0x80, np.arange(len(raw)), 0))  # a character's bytes come from its first one
        widths = np.where(raw == 0x20, len(mark), 1)
        source = np.repeat(lead, widths)
        head = len(mark) if self.prefix else 0
        return mark * bool(head) + data.replace(b" ", mark), np.concatenate([np.zeros(head, np.int64), source, [len(data)]])


class PieceCodec:
    def __init__(self, path: str, most_words: int = 200_000) -> None:
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2 as pb

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        proto = pb.ModelProto.FromString(self.model.serialized_model_proto())
        self.normalizer = Normalizer(proto.normalizer_spec)
        self.types = [p.type for p in proto.pieces]
        self.unk = (proto.trainer_spec.unk_surface or " ⁇ ").encode()
        self.surface = [bytes([int(p.piece[3:-1], 16)]) if p.type == BYTE else b"" if p.type in (CONTROL, UNKNOWN) else p.piece.encode() for p in proto.pieces]
        self.by_word = self.normalizer.plain and not any(SPACE in p.piece.lstrip(SPACE) or p.type == USER for p in proto.pieces)
        self.end, self.most = self.model.eos_id(), most_words
        self.known: dict[str, tuple[bytes, bytes] | None] = {}

    # -- whole texts ---------------------------------------------------------------------------
    def spans(self, text: str, ids: list[int]) -> np.ndarray:
        """Begin and end in original bytes for each id but the end id, by way of the alignment."""
        data = text.encode()
        normal, source = self.normalizer(data)
        lengths, at = [], 0
        for i in ids:
            if self.types[i] == UNKNOWN:  # a run of characters that no piece covers
                n = 1
                while at + n < len(normal) and normal[at + n] & 0xC0 == 0x80:
                    n += 1
            else:
                n = len(self.surface[i])
                if normal[at : at + n] != self.surface[i]:
                    raise ValueError("the pieces differ from the normalised text")
            lengths.append(n)
            at += n
        ends = np.cumsum(np.array(lengths, np.int64))
        begins = ends - lengths
        return np.stack([source[begins], source[ends]], axis=1) if len(ids) else np.zeros((0, 2), np.int64)

    def decode(self, ids: list[int]) -> str:
        """Pieces joined, marks turned to spaces, the first one dropped, byte runs read as UTF-8."""
        out: list[bytes] = []
        first = True
        for i in ids:
            kind = self.types[i]
            if kind == CONTROL:
                continue
            put = self.unk if kind == UNKNOWN else self.surface[i] if kind == BYTE else self.surface[i].replace(_MARK, b" ")
            if first and kind in (NORMAL, USER, UNUSED) and self.normalizer.prefix and put.startswith(b" "):
                put = put[1:]
            first = False
            out.append(put)
        return b"".join(out).decode("utf-8", "replace")

    # -- by word -------------------------------------------------------------------------------
    def _learn(self, words: set[str]) -> None:
        if len(self.known) + len(words) > self.most:
            self.known.clear()
        new = [w for w in words if w not in self.known]
        surface, types = self.surface, self.types
        encoded = self.model.encode(new, num_threads=1)
        for w, ids, back in zip(new, encoded, self.model.decode(encoded, num_threads=1) if new else [], strict=True):
            pieces = [surface[i] for i in ids]
            safe = w and SPACE not in w and b"".join(pieces) == _MARK + w.encode() and types[ids[0]] != BYTE
            self.known[w] = (np.array(ids, np.int32).tobytes(), np.array([len(p) for p in pieces], np.int32).tobytes(), back) if safe else None

    def encode(self, texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray, str]]:
        """ids (with the end id), ends of the original byte spans (a span begins where the last ended), decoded text."""
        texts = [t or "" for t in texts]
        for i, j in slices(texts, 1_000_000):
            some = texts[i:j]
            parts = [t.split(" ") for t in some] if self.by_word else None
            if parts:
                self._learn(set(chain.from_iterable(parts)))
            for n, text in enumerate(some):
                got = list(map(self.known.__getitem__, parts[n])) if parts else [None]
                if None in got:
                    ids = self.model.encode(text)
                    spans = self.spans(text, ids)
                    yield np.array([*ids, self.end], np.int32), np.append(spans[:, 1], len(text.encode())), self.decode(ids)
                    continue
                ids, lengths, back = zip(*got, strict=True)
                normal, source = self.normalizer(text.encode())
                at = np.cumsum(np.frombuffer(b"".join(lengths), np.int32), dtype=np.int64)
                if at[-1] != len(normal):
                    raise ValueError("the pieces differ from the normalised text")
                ends = source[at]
                yield np.frombuffer(b"".join(ids) + self.end.to_bytes(4, "little"), np.int32), np.append(ends, ends[-1]), " ".join(back)


def codec(path: str) -> PieceCodec:
    if path not in _CODECS:
        _CODECS[path] = PieceCodec(path)
    return _CODECS[path]


def encode_column(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids array<int> (with the end id), span_ends array<long> (end in original bytes of each id; the
    begin is the end before it), decoded string (read from the ids)."""
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32())), ("span_ends", pa.list_(pa.int32())), ("decoded", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = codec(model_path)
        for batch in in_pieces(batches, 1):
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for i, j in slices(texts, 1_000_000):
                ids, ends, decoded = zip(*coder.encode(texts[i:j]), strict=True)
                offsets = pa.array(np.cumsum([0, *map(len, ids)]), pa.int32())
                columns = [batch.column(0).slice(i, j - i), pa.ListArray.from_arrays(offsets, pa.array(np.concatenate(ids))), pa.ListArray.from_arrays(offsets, pa.array(np.concatenate(ends).astype(np.int32))), pa.array(decoded, pa.string())]
                yield pa.RecordBatch.from_arrays(columns, schema=schema)

    wanted = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return wanted.mapInArrow(run, "doc_id long, ids array<int>, span_ends array<int>, decoded string")


def digests(encoded: DataFrame) -> DataFrame:
    return encoded.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), " "), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
        F.sha2(F.array_join(F.col("span_ends").cast("array<string>"), " "), 256).alias("spans_sha256"),
    )
