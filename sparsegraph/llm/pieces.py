"""SentencePiece encoding with offsets, and decoding.

Normalisation is done here: at each position the longest prefix that the model's compiled character map (a double-array
trie and a pool of replacements) knows is replaced, every normalised byte remembers the span of original bytes it came
from, and white space is collapsed, prefixed and escaped as the model's options say. The normalised text goes to the library's encoder with its own normaliser
switched off, so the pieces are those of the bytes made here; their lengths, laid over the alignment, give every piece its
span of the original UTF-8 bytes. Models that put white space after words are refused.

Null counts as the empty text: begin and end id alone. Repeated rows are encoded each for itself. Very long texts are
encoded whole. Other columns stay as they are."""

from __future__ import annotations

import hashlib
import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_rows, schema_of

SPACE = "▁".encode()


class CharacterMap:
    """The compiled map of a normaliser: 4 bytes of trie size, the trie's units, then replacements that end with zero."""

    def __init__(self, blob: bytes):
        self.units: tuple[int, ...] = ()
        self.pool = b""
        if len(blob) > 4:
            size = struct.unpack_from("<I", blob)[0]
            self.units = struct.unpack_from(f"<{size // 4}I", blob, 4)
            self.pool = blob[4 + size :]

    @staticmethod
    def _offset(unit: int) -> int:
        return unit >> 10 << ((unit & 0x200) >> 6)

    def longest(self, text: bytes, at: int) -> tuple[int, bytes] | None:
        """(bytes matched, replacement) of the longest known prefix of text[at:]."""
        if not self.units:
            return None
        found = None
        node = self._offset(self.units[0])
        for k in range(at, len(text)):
            node ^= text[k]
            if node >= len(self.units):
                break
            unit = self.units[node]
            if unit & 0x800000FF != text[k]:
                break
            node ^= self._offset(unit)
            if unit >> 8 & 1:
                value = self.units[node] & 0x7FFFFFFF
                found = (k + 1 - at, self.pool[value : self.pool.index(b"\0", value)])
        return found


def utf8_length(first: int) -> int:
    return 1 if first < 0x80 else 2 if first < 0xE0 else 3 if first < 0xF0 else 4


class Normaliser:
    """A model's normaliser that records alignment."""

    def __init__(self, spec):
        self.map = CharacterMap(spec.precompiled_charsmap)
        self.add_prefix, self.collapse, self.escape = spec.add_dummy_prefix, spec.remove_extra_whitespaces, spec.escape_whitespaces
        self.space = SPACE if self.escape else b" "

    def step(self, text: bytes, at: int) -> tuple[int, bytes]:
        if found := self.map.longest(text, at):
            return found
        n = utf8_length(text[at])
        return n, text[at : at + n]

    def align(self, text: bytes) -> tuple[bytes, np.ndarray, np.ndarray]:
        """The normalised bytes, and for each of them where the original bytes that it stands for begin and end. The added
        prefix stands for none."""
        if not self.map.units and not self.collapse:
            return self._plain(text)
        out, start, end = bytearray(), [], []
        at = 0
        if self.collapse:
            while at < len(text):
                n, new = self.step(text, at)
                if new != b" ":
                    break
                at += n
        if at == len(text):
            return b"", np.zeros(0, np.int64), np.zeros(0, np.int64)

        def put(piece: bytes, a: int, b: int) -> None:
            out.extend(piece)
            start.extend([a] * len(piece))
            end.extend([b] * len(piece))

        if self.add_prefix:
            put(self.space, at, at)
        after_space = self.collapse
        while at < len(text):
            n, new = self.step(text, at)
            while after_space and new.startswith(b" "):
                new = new[1:]
            for b in (new[i : i + 1] for i in range(len(new))):
                put(self.space if b == b" " else b, at, at + n)
            if new:
                after_space = self.collapse and new.endswith(b" ")
            at += n
        while self.collapse and out.endswith(self.space):
            for held in (out, start, end):
                del held[-len(self.space) :]
        return bytes(out), np.array(start, np.int64), np.array(end, np.int64)

    def _plain(self, text: bytes) -> tuple[bytes, np.ndarray, np.ndarray]:
        """No character map, no collapsing: only spaces grow and a prefix may come first."""
        if not text:
            return b"", np.zeros(0, np.int64), np.zeros(0, np.int64)
        width = np.where(np.frombuffer(text, np.uint8) == 0x20, len(self.space), 1)
        start = np.repeat(np.arange(len(text)), width)
        prefix = np.zeros(len(self.space) if self.add_prefix else 0, np.int64)
        return (self.space if self.add_prefix else b"") + text.replace(b" ", self.space), np.concatenate((prefix, start)), np.concatenate((prefix, start + 1))


class PieceModel:
    def __init__(self, blob: bytes):
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2

        self.library = sentencepiece.SentencePieceProcessor(model_proto=blob)
        proto = sentencepiece_model_pb2.ModelProto()
        proto.ParseFromString(blob)
        if proto.trainer_spec.treat_whitespace_as_suffix:
            raise NotImplementedError("white space after words")
        plain = sentencepiece_model_pb2.ModelProto()
        plain.CopyFrom(proto)
        plain.normalizer_spec.precompiled_charsmap = b""
        plain.normalizer_spec.add_dummy_prefix = plain.normalizer_spec.remove_extra_whitespaces = plain.normalizer_spec.escape_whitespaces = False
        self.encoder = sentencepiece.SentencePieceProcessor(model_proto=plain.SerializeToString())
        self.normaliser = Normaliser(proto.normalizer_spec)
        self.length = [1 if p.type == p.BYTE else len(p.piece.encode()) for p in proto.pieces]
        self.unknown = {i for i, p in enumerate(proto.pieces) if p.type == p.UNKNOWN}

    def encode(self, texts: list[str]) -> tuple[list[list[int]], list[tuple[bytes, np.ndarray, np.ndarray]]]:
        """The ids of each text, and its alignment."""
        aligned = [self.normaliser.align(t.encode()) for t in texts]
        return self.encoder.encode([a[0].decode() for a in aligned], add_bos=True, add_eos=True, num_threads=1), aligned

    def decode(self, ids: list[list[int]]) -> list[str]:
        return self.library.decode(ids, num_threads=1) if ids else []

    def spans(self, size: int, ids: list[int], aligned: tuple[bytes, np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Start and end of each id in the `size` original bytes; begin and end ids are empty. A piece of an unknown
        character covers what the library says."""
        normal, first, last = aligned
        inner = ids[1:-1]
        if self.unknown.isdisjoint(inner):
            width = [self.length[i] for i in inner]
        else:
            pieces = self.encoder.encode(normal.decode(), return_type="proto").pieces
            width = [len(p.surface.encode()) if p.id in self.unknown else self.length[p.id] for p in pieces]
        edge = np.concatenate(([0], np.cumsum(np.array(width, np.int64))))
        if edge[-1] != len(normal):
            raise ValueError("pieces do not add up to the normalised text")
        start, end = (first[edge[:-1]], last[edge[1:] - 1]) if inner else (first[:0], last[:0])
        return np.concatenate(([0], start, [size])), np.concatenate(([0], end, [size]))


def lists(arrays: list[np.ndarray]) -> pa.ListArray:
    edge = np.concatenate(([0], np.cumsum([len(a) for a in arrays]))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(edge), pa.array(np.concatenate(arrays) if arrays else np.zeros(0, np.int32)))


def load(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def digest(ids: list[int]) -> str:
    return hashlib.sha256(np.asarray(ids, "<u4").tobytes()).hexdigest()


def encode(docs: DataFrame, model_path: str, *, text_col: str = "text", offsets: bool = True, keep: list[str] | None = None) -> DataFrame:
    """docs (or its columns `keep`) plus ids, with begin and end id, and with `offsets` piece_start and piece_end in bytes
    of the UTF-8 text. Columns of these names in docs give way. The model is broadcast: half a megabyte."""
    shared = docs.sparkSession.sparkContext.broadcast(load(model_path))
    docs = docs.drop("ids", "piece_start", "piece_end")
    kept = keep or docs.columns
    more = ["ids array<int>"] + ["piece_start array<int>", "piece_end array<int>"] * offsets
    held: dict[str, PieceModel] = {}

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not held:
            held["model"] = PieceModel(shared.value)
        model = held["model"]
        texts = [t or "" for t in batch.column(text_col).to_pylist()]
        ids, aligned = model.encode(texts)
        columns = [lists([np.asarray(i, np.int32) for i in ids])]
        if offsets:
            spans = [model.spans(len(t.encode()), i, a) for t, i, a in zip(texts, ids, aligned, strict=True)]
            columns += [lists([s[k].astype(np.int32) for s in spans]) for k in (0, 1)]
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), *columns], names=[*kept, *(m.split()[0] for m in more)])

    return map_rows(docs, run, schema_of(docs.select(*kept), *more))


def round_trip(docs: DataFrame, model_path: str, *, check_offsets: bool = True) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256, n_aligned): digests of the ids and of the decoded text, and the
    number of pieces whose span of the original is not empty."""
    shared = docs.sparkSession.sparkContext.broadcast(load(model_path))
    held: dict[str, PieceModel] = {}

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not held:
            held["model"] = PieceModel(shared.value)
        model = held["model"]
        texts = [t or "" for t in batch.column("text").to_pylist()]
        ids, aligned = model.encode(texts)
        decoded = model.decode(ids)
        covered = []
        for t, i, a in zip(texts, ids, aligned, strict=True):
            start, end = model.spans(len(t.encode()), i, a)
            covered.append(int((end > start).sum()))
        return pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "n_tokens": pa.array([len(i) for i in ids], pa.int64()), "ids_sha256": [digest(i) for i in ids], "decoded_sha256": [hashlib.sha256(d.encode()).hexdigest() for d in decoded], "n_aligned": pa.array(covered, pa.int64())})

    return map_rows(docs.select("doc_id", "text"), run, schema_of(docs.select("doc_id"), "n_tokens long", "ids_sha256 string", "decoded_sha256 string", "n_aligned long"))
