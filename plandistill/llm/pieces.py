"""SentencePiece encoding and decoding with an automaton over the pieces.

The pieces of a model file form an Aho-Corasick automaton. Encoding reads a
text once; at every position the matches that end there (the chain of output
links) relax the best score of that position: the segmentation with the
highest sum of piece scores, as the library's unigram mode finds it for the
same pieces. Characters without a piece become byte pieces (or the unknown
piece, if the model has none). No piece has a space mark after another
character, so a text falls into segments at its space marks, and a segment's
ids are remembered by each worker (at most ``CACHE`` of them).

A space mark that stands in the text itself is written as its three byte pieces, so it
isn't taken for a space. Decoding joins pieces and bytes and turns marks into
spaces; with a model that has byte pieces it gives back the text exactly. A model without
them has its unknown piece for what it can't spell, and that isn't given back.

Defined results: a null or empty text has no pieces and decodes to the empty
text; repeated rows encode alike; an empty table gives no rows; other columns
pass untouched in the stage and aren't read otherwise.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import sliced

MARK, CACHE = "▁", 250_000
#: How much worse than the worst piece a character without a piece is (the library's constant).
UNKNOWN_PENALTY = 10.0
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(number, value) of the fields of one protocol-buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
        elif kind == 5:
            at += 4
            yield key >> 3, data[at - 4 : at]
        elif kind == 1:
            at += 8
            yield key >> 3, data[at - 8 : at]
        else:
            n = varint()
            at += n
            yield key >> 3, data[at - n : at]


def load_pieces(path: str) -> list[tuple[str, float, int]]:
    """(piece, score, type) of a model file, in the order of their ids."""
    out = []
    for number, value in _fields(open(path, "rb").read()):
        if number == 1:
            got = dict(_fields(value))
            out.append((got[1].decode(), struct.unpack("<f", got[2])[0] if 2 in got else 0.0, got.get(3, NORMAL)))
    return out


class Segmenter:
    """Encodes and decodes with the pieces of one model file."""

    def __init__(self, path: str):
        import ahocorasick

        self.pieces = load_pieces(path)
        self.bytes = {int(p[3:5], 16): i for i, (p, _, t) in enumerate(self.pieces) if t == BYTE}
        self.of_byte = {i: b for b, i in self.bytes.items()}
        self.unknown = next((i for i, (_, _, t) in enumerate(self.pieces) if t == UNKNOWN), 0)
        usable = [(p, s, i) for i, (p, s, t) in enumerate(self.pieces) if t in (NORMAL, USER)]
        if any(re.search(f"[^{MARK}]{MARK}", p) for p, _, _ in usable):
            raise ValueError("a piece crosses a space mark: texts don't fall into segments")
        self.floor = min((s for _, s, _ in usable), default=0.0) - UNKNOWN_PENALTY
        self.machine = ahocorasick.Automaton()
        for p, s, i in usable:
            self.machine.add_word(p, (len(p), s, i))
        self.machine.make_automaton()
        self.known: dict[str, bytes] = {}
        # a line end that no piece holds parts segments too
        cut = "" if any("\n" in p for p, _, _ in usable) else "\n"
        self.segment = re.compile(f"{MARK}*[^{MARK}{cut}]+|{MARK}+" + f"|{cut}" * bool(cut))

    def _viterbi(self, x: str) -> list[int]:
        n = len(x)
        best, back = [0.0] + [-np.inf] * n, [None] * (n + 1)
        matches, done = self.machine.iter(x), 0
        at, (size, score, piece) = next(matches, (n, (0, 0.0, -1)))
        for end in range(n):  # positions in order; each takes the matches that end there
            alone = False
            while at == end:
                total = best[end + 1 - size] + score
                alone |= size == 1
                if total > best[end + 1]:
                    best[end + 1], back[end + 1] = total, (size, piece)
                at, (size, score, piece) = next(matches, (n, (0, 0.0, -1)))
            if not alone and best[end] + self.floor > best[end + 1]:
                best[end + 1], back[end + 1] = best[end] + self.floor, (1, -1)
        out, end = [], n
        while end:
            size, piece = back[end]
            out.append((end - size, piece))
            end -= size
        ids: list[int] = []
        for start, piece in reversed(out):
            if piece >= 0:
                ids.append(piece)
            elif self.bytes:
                ids.extend(self.bytes[b] for b in x[start].encode("utf-8", "surrogatepass"))
            elif not ids or ids[-1] != self.unknown:
                ids.append(self.unknown)
        return ids

    def encode(self, text: str) -> np.ndarray:
        """Ids of a text (identity normalisation, a space mark before the first character)."""
        if not text:
            return np.empty(0, np.uint32)
        spelled = [self.bytes[b] for b in MARK.encode()] if self.bytes else [self.unknown]
        literal = np.array(spelled, "<u4").tobytes()
        first, *more = text.split(MARK)
        parts = [self._encoded(MARK + first.replace(" ", MARK))]
        for x in more:  # the text's own marks
            parts += [literal, self._encoded(x.replace(" ", MARK))]
        return np.frombuffer(b"".join(parts), "<u4")

    def _encoded(self, marked: str) -> bytes:
        parts = self.segment.findall(marked)
        new = [p for p in set(parts) if p not in self.known]
        if len(self.known) + len(new) > CACHE:
            self.known.clear()
            new = set(parts)
        for p in new:
            self.known[p] = np.array(self._viterbi(p), "<u4").tobytes()
        return b"".join(map(self.known.__getitem__, parts))

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids; a mark at the start is the one that encoding put there."""
        if not len(ids):
            return ""
        table = self._spelled()
        text = b"".join(map(table.__getitem__, ids.tolist())).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text

    def _spelled(self) -> list[bytes]:
        if not hasattr(self, "spelled"):
            skip = (CONTROL, UNKNOWN)
            self.spelled = [bytes([self.of_byte[i]]) if i in self.of_byte else b"" if t in skip else p.replace(MARK, " ").encode() for i, (p, _, t) in enumerate(self.pieces)]
        return self.spelled


_open: dict[str, Segmenter] = {}


def segmenter(path: str) -> Segmenter:
    if path not in _open:
        _open[path] = Segmenter(path)
    return _open[path]


def encode_texts(docs: DataFrame, model: str, columns: list[str]) -> DataFrame:
    """The named columns of ``docs`` with ids (array of int) and decoded (the text that the
    ids give back): one pass, no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = segmenter(model)
        for b in sliced(batches):
            ids = [s.encode(t or "") for t in b.column(0).to_pylist()]
            made = [pa.array([x.view(np.int32) for x in ids], pa.list_(pa.int32())), pa.array([s.decode(x) for x in ids], pa.string())]
            yield pa.RecordBatch.from_arrays([b.column(1), *made], names=["row", "ids", "decoded"])

    carried = docs.select("text", F.struct(*columns).alias("row"))
    kind = carried.schema["row"].dataType.simpleString()
    return carried.mapInArrow(run, f"row {kind}, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, model: str, id_col: str = "doc_id") -> DataFrame:
    """Per document: id, n_chars, n_pieces, n_bytes (byte pieces), ids_crc32 (of the ids as
    little-endian unsigned 32-bit integers), same (decoding gives back the text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = segmenter(model)
        is_byte = np.zeros(len(s.pieces), bool)
        is_byte[list(s.of_byte)] = True
        for b in sliced(batches):
            texts = [t or "" for t in b.column(1).to_pylist()]
            ids = [s.encode(t) for t in texts]
            longs = lambda values: pa.array(values, pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), longs([len(t) for t in texts]), longs([len(x) for x in ids]), longs([int(is_byte[x].sum()) for x in ids]), longs([zlib.crc32(x.tobytes()) for x in ids]), pa.array([s.decode(x) == t for x, t in zip(ids, texts, strict=True)])], names=["id", "n_chars", "n_pieces", "n_bytes", "ids_crc32", "same"])

    kind = dict(docs.dtypes)[id_col]
    return docs.select(F.col(id_col).alias("id"), "text").mapInArrow(run, f"id {kind}, n_chars long, n_pieces long, n_bytes long, ids_crc32 long, same boolean").withColumnRenamed("id", id_col)


def decode_ids(encoded: DataFrame, model: str, id_col: str = "doc_id") -> DataFrame:
    """id and text for rows of id, ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = segmenter(model)
        for b in sliced(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([s.decode(np.array(x or [], np.uint32)) for x in b.column(1).to_pylist()], pa.string())], names=["id", "text"])

    kind = dict(encoded.dtypes)[id_col]
    return encoded.select(F.col(id_col).alias("id"), "ids").mapInArrow(run, f"id {kind}, text string").withColumnRenamed("id", id_col)
