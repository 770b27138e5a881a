"""Token ids in a block file with one shared compression dictionary.

The store is a folder with two Parquet tables. ``header`` has one row: the
trained dictionary, its hash, the width of an id and the end id. ``blocks`` has
rows of at most about ``BLOCK_BYTES`` of frames in ascending order of document:
each document is one zstandard frame made with the dictionary, and the row
holds the offset and length of every frame, so one short document is read by
decompressing its own few bytes only. First and last id of a block are plain
columns: a lookup prunes row groups.

Defined results: a null text is the empty text; equal ids keep all their rows,
ordered by a hash of the text; a null id sorts first; an empty table gives an
empty store; other columns are not read.
"""

from __future__ import annotations

import hashlib
import json
import os
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard as zstd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import sliced

BLOCK_BYTES = 128 << 10
#: Documents and bytes of each that the dictionary is trained on, at most.
SAMPLE_DOCS, SAMPLE_BYTES, DICTIONARY_BYTES = 1_000, 32 << 10, 64 << 10
#: Distinct chunks whose ids one worker remembers, in each of two generations.
CACHE = 350_000
#: Marks that may end a chunk (no apostrophe: some endings with one are pre-tokens).
MARKS = ".,;:!?#$%&*|+=/()[]{}<>~^@_-"

BLOCKS = "part int, block long, dictionary string, first_doc long, last_doc long, n_tokens long, doc_ids array<long>, offsets array<long>, lengths array<long>, payload binary"


class Chunks:
    """Ids of white-space parted chunks as bytes, asked from the tokenizer once each.

    Spaces and line ends part pre-tokens in this kind of tokenizer (they are
    dropped before the merges), so a text's ids are its chunks' ids in a row.
    Texts of Latin letters are put in lower case first. Chunks of small letters
    alone skip the steps that leave them as they are, and a run of marks after
    them is a pre-token of its own. Two generations are kept: what is asked for again moves to the
    young one, so frequent chunks stay however large the corpus is.
    """

    #: Small letters that no step changes, then a run of marks.
    WORD = re.compile(f"([a-z\xdf-\xf6\xf8-\xff]+)([{re.escape(MARKS)}]*)").fullmatch
    ASKED_AT_ONCE, AT_ONCE = 400, 12 << 20

    def __init__(self, path: str, width: int):
        from tokenizers import Tokenizer, pre_tokenizers

        self.whole, self.code = Tokenizer.from_file(path), {2: "H", 4: "I"}[width]
        self.letters = Tokenizer(self.whole.model)
        self.letters.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        end = json.loads(self.whole.to_str())["model"].get("end_of_word_suffix") or ""
        self.ends = np.zeros(1 << 8 * width if width == 2 else self.whole.get_vocab_size(), bool)
        self.ends[[i for x, i in self.whole.get_vocab().items() if end and x.endswith(end)]] = True
        self.young, self.old = {"": b""}, {}
        self.short = bool(end) and self._short_way_holds()

    def _short_way_holds(self) -> bool:
        """Whether this tokenizer gives the same on a probe the short way."""
        ids = lambda t, x: t.encode(x, add_special_tokens=False).ids
        return all(ids(self.whole, f"{x}.,#! y, z") == ids(self.letters, x.lower()) + ids(self.whole, ".,#!") + ids(self.whole, "y , z") for x in ("Word", "ÉTÉ", "straße", "Ñandú", "a", "\u017f"))

    def _ask(self, asked: list[str]) -> None:
        code = self.code
        self.young.update((x, array(code, e.ids).tobytes()) for x, e in zip(asked, self.whole.encode_batch(asked, add_special_tokens=False), strict=True))

    def _ask_letters(self, asked: list[str]) -> None:
        """Many words in one text: the marks of word ends in the ids part them again."""
        size, step = array(self.code).itemsize, self.ASKED_AT_ONCE
        runs = [asked[i : i + step] for i in range(0, len(asked), step)]
        for run, e in zip(runs, self.letters.encode_batch_fast([" ".join(r) for r in runs], add_special_tokens=False), strict=True):
            ids = array(self.code, e.ids)
            cuts = ((np.flatnonzero(self.ends[np.frombuffer(ids, self.code)]) + 1) * size).tolist()
            if len(cuts) != len(run):
                raise ValueError("words and word ends differ")
            raw = ids.tobytes()
            self.young.update(zip(run, [raw[i:j] for i, j in zip([0, *cuts], cuts)], strict=True))  # noqa: B905

    def encode(self, texts: pa.Array) -> list[bytes]:
        """Ids of each text as bytes; null is the empty text."""
        texts = pc.fill_null(texts.cast(pa.string()), "")
        out, start, size = [], 0, 0
        for i, n in enumerate(pc.binary_length(texts).to_pylist()):
            size += n
            if size > self.AT_ONCE:
                out += self._encode(texts.slice(start, i + 1 - start))
                start, size = i + 1, 0
        return out + self._encode(texts.slice(start)) if start < len(texts) else out

    def _encode(self, texts: pa.Array) -> list[bytes]:
        """Chunks are numbered first, so each different one of these texts is looked up once."""
        odd = pc.match_substring_regex(texts, "[^\\x{00}-\\x{24f}]|[\\x{130}\\x{1c}-\\x{1f}]").to_numpy(zero_copy_only=False)
        if not self.short:
            odd[:] = True
        lists = pc.utf8_split_whitespace(pc.utf8_lower(texts.filter(pa.array(~odd))))
        plain = self._gathered(lists.flatten(), lists.offsets.to_numpy() - lists.offsets[0].as_py())
        if not odd.any():
            return plain
        parts = [t.replace("\n", " ").split(" ") for t in texts.filter(pa.array(odd)).to_pylist()]
        rare = iter(self._gathered(pa.array([x for p in parts for x in p], pa.string()), np.cumsum([0, *map(len, parts)])))
        usual = iter(plain)
        return [next(rare if o else usual) for o in odd]

    def _gathered(self, chunks: pa.Array, offsets: np.ndarray) -> list[bytes]:
        if len(self.young) > CACHE:
            self.young, self.old = {"": b""}, self.young
        numbered = chunks.dictionary_encode()
        different, number = numbered.dictionary.to_pylist(), numbered.indices.to_numpy()
        found = list(map(self.young.get, different))
        new = {x for x, y in zip(different, found, strict=True) if y is None}
        if new:
            self._learn(new)
            sure = self.young.__getitem__
            found = [sure(x) if y is None else y for x, y in zip(different, found, strict=True)]
        size = array(self.code).itemsize
        pool = np.frombuffer(b"".join(found), self.code)
        long = np.fromiter(map(len, found), np.int32, len(found)) // np.int32(size)
        first = np.cumsum(long, dtype=np.int32) - long
        each = long[number]
        ends = np.cumsum(each, dtype=np.int32)
        at = np.arange(ends[-1] if len(ends) else 0, dtype=np.int32)
        at += np.repeat(first[number] - (ends - each), each)
        ids = pool[at]
        cuts = (np.concatenate([[0], ends])[offsets] * size).tolist()
        raw = ids.tobytes()
        return [raw[i:j] for i, j in zip(cuts, cuts[1:], strict=False)]

    def _learn(self, new: set[str]) -> None:
        young, old = self.young, self.old
        if old:
            again = new & old.keys()
            young.update((x, old[x]) for x in again)
            new -= again
        stems = {x: m.groups() for x in new if (m := self.WORD(x))} if self.short else {}
        if stems:
            new.difference_update(stems)
            plain = [x for x in {stem for stem, _ in stems.values()} if x not in young]
            if plain:
                self._ask_letters(plain)
            new.update(tail for _, tail in stems.values())
            new.difference_update(young)
        if new:
            self._ask(list(new))
        for x, (stem, tail) in stems.items():
            if tail:
                young[x] = young[stem] + young[tail]


_open: dict[tuple[str, int], Chunks] = {}


def chunks(path: str, width: int) -> Chunks:
    """This worker's memory of chunks, kept between tasks."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    if (path, width) not in _open:
        _open[path, width] = Chunks(path, width)
    return _open[path, width]


def id_width(path: str) -> int:
    from tokenizers import Tokenizer

    return 2 if Tokenizer.from_file(path).get_vocab_size() <= 1 << 16 else 4


def train_dictionary(samples: list[bytes]) -> bytes:
    """A trained dictionary; raw content where there is too little to train on."""
    samples = [s for s in samples if s]
    try:
        return zstd.train_dictionary(DICTIONARY_BYTES, samples).as_bytes()
    except (zstd.ZstdError, ValueError):
        return b"".join(samples)[:DICTIONARY_BYTES]


def _dictionary_sample(docs: DataFrame, path: str, width: int, end_id: int) -> list[bytes]:
    """Serialised ids of the documents with the smallest hashes of their id."""
    ids = [r[0] for r in docs.select("doc_id").where("doc_id is not null").orderBy(F.xxhash64("doc_id"), "doc_id").limit(SAMPLE_DOCS).collect()]
    if not ids:
        return []
    end = np.array([end_id], f"<u{width}").tobytes()

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            yield pa.RecordBatch.from_pydict({"x": [(x + end)[:SAMPLE_BYTES] for x in chunks(path, width).encode(b.column(0))]})

    picked = docs.where(F.col("doc_id").isin(ids)).select("text")
    return [bytes(r[0]) for r in picked.mapInArrow(encoded, "x binary").limit(SAMPLE_DOCS).collect()]


def write_tokens(docs: DataFrame, tokenizer: str, path: str, end_id: int = 2) -> str:
    """Encode whole texts and write the store; returns the dictionary's hash."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    width = id_width(tokenizer)
    dictionary = train_dictionary(_dictionary_sample(docs, tokenizer, width, end_id))
    tag = hashlib.sha256(dictionary).hexdigest()
    spark.createDataFrame([(tag, bytearray(dictionary), width, end_id)], "dictionary string, content binary, width int, end_id int").coalesce(1).write.parquet(f"{path}/header")
    shared = spark.sparkContext.broadcast(dictionary)  # DICTIONARY_BYTES at most
    end = np.array([end_id], f"<u{width}").tobytes()

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, part, block = chunks(tokenizer, width), TaskContext.get().partitionId(), 0
        press = zstd.ZstdCompressor(level=3, dict_data=zstd.ZstdCompressionDict(shared.value) if shared.value else None, write_content_size=True)
        ids, frames, tokens = [], [], 0

        def flush() -> pa.RecordBatch:
            nonlocal ids, frames, tokens, block
            lengths = [len(f) for f in frames]
            offsets = np.concatenate([[0], np.cumsum(lengths)[:-1]]).astype("i8").tolist()
            known = [i for i in ids if i is not None]
            row = {"part": [part], "block": [block], "dictionary": [tag], "first_doc": [min(known, default=None)], "last_doc": [max(known, default=None)], "n_tokens": [tokens], "doc_ids": [ids], "offsets": [offsets], "lengths": [lengths], "payload": [b"".join(frames)]}
            ids, frames, tokens, block = [], [], 0, block + 1
            return pa.RecordBatch.from_pydict(row, schema=arrow)

        size = 0
        for b in sliced(batches, 4_000):
            for doc, x in zip(b.column(0).to_pylist(), cache.encode(b.column(1)), strict=True):
                frames.append(press.compress(x + end))
                ids.append(doc)
                tokens += len(x) // width + 1
                size += len(frames[-1])
                if size >= BLOCK_BYTES:
                    size = 0
                    yield flush()
        if ids:
            yield flush()

    longs = pa.list_(pa.int64())
    arrow = pa.schema([("part", pa.int32()), ("block", pa.int64()), ("dictionary", pa.string()), ("first_doc", pa.int64()), ("last_doc", pa.int64()), ("n_tokens", pa.int64()), ("doc_ids", longs), ("offsets", longs), ("lengths", longs), ("payload", pa.binary())])
    ordered = docs.repartitionByRange(F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"), "text")
    ordered.mapInArrow(blocks, BLOCKS).write.parquet(f"{path}/blocks")
    return tag


def _opened(spark: SparkSession, path: str) -> tuple[str, bytes, int, int]:
    tag, content, width, end_id = spark.read.parquet(f"{path}/header").head()
    if hashlib.sha256(bytes(content)).hexdigest() != tag:
        raise ValueError("the dictionary doesn't match its hash")
    return tag, bytes(content), width, end_id


def _inflate(content: bytes) -> zstd.ZstdDecompressor:
    return zstd.ZstdDecompressor(dict_data=zstd.ZstdCompressionDict(content)) if content else zstd.ZstdDecompressor()


def read_digests(spark: SparkSession, path: str) -> DataFrame:
    """Per document, from the stored frames: doc_id, start, n_tokens, ids_crc32, frame_bytes."""
    tag, content, width, _ = _opened(spark, path)
    shared = spark.sparkContext.broadcast(content)

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        inflate = _inflate(shared.value)
        for b in sliced(batches):
            out = {k: [] for k in ("part", "block", "pos", "doc_id", "n_tokens", "ids_crc32", "frame_bytes")}
            for r in b.to_pylist():
                if r["dictionary"] != tag:
                    raise ValueError("a block was made with another dictionary")
                view = memoryview(r["payload"])
                for i, (doc, at, n) in enumerate(zip(r["doc_ids"], r["offsets"], r["lengths"], strict=True)):
                    ids = np.frombuffer(inflate.decompress(view[at : at + n]), f"<u{width}")
                    for k, v in zip(out, (r["part"], r["block"], i, doc, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), n), strict=True):
                        out[k].append(v)
            yield pa.RecordBatch.from_pydict(out, schema=arrow)

    arrow = pa.schema([("part", pa.int32()), ("block", pa.int64()), ("pos", pa.int32())] + [(k, pa.int64()) for k in ("doc_id", "n_tokens", "ids_crc32", "frame_bytes")])
    stored = spark.read.parquet(f"{path}/blocks")
    rows = stored.select("part", "block", "dictionary", "doc_ids", "offsets", "lengths", "payload").mapInArrow(digests, "part int, block long, pos int, doc_id long, n_tokens long, ids_crc32 long, frame_bytes long")
    # one row for each written part: as many as the writing job had tasks
    parts = stored.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    bases = parts.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    before = Window.partitionBy("part").orderBy("block", "pos").rowsBetween(Window.unboundedPreceding, -1)
    return rows.join(bases, "part").select("doc_id", (F.col("base") + F.coalesce(F.sum("n_tokens").over(before), F.lit(0))).alias("start"), "n_tokens", "ids_crc32", "frame_bytes")


def read_document(spark: SparkSession, path: str, doc_id: int) -> list[list[int]]:
    """Ids of one document (of each row with that id), decompressing its frames alone."""
    tag, content, width, _ = _opened(spark, path)
    inflate, found = _inflate(content), []
    near = spark.read.parquet(f"{path}/blocks").where((F.col("first_doc") <= doc_id) & (F.col("last_doc") >= doc_id))
    frames = near.select("part", "block", "payload", F.posexplode(F.arrays_zip("doc_ids", "offsets", "lengths")).alias("pos", "z")).where(F.col("z.doc_ids") == doc_id)
    for r in frames.orderBy("part", "block", "pos").select(F.expr("substring(payload, int(z.offsets) + 1, int(z.lengths))").alias("x")).collect():
        found.append(np.frombuffer(inflate.decompress(bytes(r[0])), f"<u{width}").tolist())
    return found
