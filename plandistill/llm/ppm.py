"""Scores of texts by prediction by partial matching over bytes, and by word counts.

Pretrained form: the trie holds, for each context of up to ``ORDER`` bytes, how
often each byte followed it in the training texts; counts of shorter contexts
are sums of longer ones, so the symbols of a context are among those of its
suffix. A byte's probability is c / (n + d) in the longest context that has it,
after the escapes d / (n + d) of longer ones, where d is the context's number
of distinct symbols (0 if it has all, as nothing can escape) and n counts without the symbols that longer contexts have
excluded; below order 0 all bytes that were not seen share the rest evenly. With fixed counts
this depends on context and byte only. What a context excludes in the next shorter one
changes only the divisor there, so the trie folds into a dense table over three bytes and one
escape for each longer context, exactly, and texts are scored by lookups. Every string counted has its
leaf: the most frequent, at most ``2 ** LEAF_BITS``, go to the executors with the
escapes of all contexts (at most ``2 ** 24``); the others are joined, as rare
words are. A leaf's n and d are those of all strings of its context.

Adaptive form (``adaptive_score``): the trie starts empty, or from a text, and
learns each byte after it is coded.

Word baseline: log10((c + 0.1) / (N + 0.1 (V + 1))) over words and one end
token, with counts from the training texts. Words that make up ``2 ** -20`` of
the tokens or more (at most a million) go to the executors as a table; the others
are joined.

Defined results: null text is the empty text (one end token, PPM score 0);
a null id is held in training by its hash text being null (remainder null
counts as training); rows that share an id are scored apart; an empty table gives no rows;
other columns are not read.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import park, sliced

ORDER, LEAF_BITS, WORD_BITS = 3, 21, 20
#: The end token; words hold no line end.
END = b"\n"
START_CONTEXT = b"\n\n\n"


def held_out(doc_id: Column, fold: int = 10) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % fold == 0, F.lit(False))


def _bytes(column: pa.Array) -> list[bytes]:
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def tokens(text: bytes) -> list[bytes]:
    """Words in ASCII lower case (only ASCII white space parts them), then the end."""
    found = text.lower().split()
    found.append(END)
    return found


# --- counting -------------------------------------------------------------------------------

FLUSH = 400_000


def _word_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen: Counter = Counter()

    def out() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(list(seen.keys()), pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["word", "c"])

    for b in sliced(batches):
        for t in _bytes(b.column(0)):
            seen.update(tokens(t))
        if len(seen) > FLUSH:
            yield out()
            seen.clear()
    if seen:
        yield out()


def four_grams(texts: list[bytes]) -> np.ndarray:
    """Of every byte the number made of it and the three bytes before it."""
    raw = np.frombuffer(b"".join(START_CONTEXT + t for t in texts), np.uint8).astype(np.uint32)
    grams = (raw[:-3] << np.uint32(24)) | (raw[1:-2] << np.uint32(16)) | (raw[2:-1] << np.uint32(8)) | raw[3:]
    ends = np.cumsum([len(t) + 3 for t in texts])[:-1]  # grams that end in the next text's start context
    keep = np.ones(len(grams), bool)
    for k in range(3):
        keep[ends - 3 + k] = False
    return grams[keep]


def _gram_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    keys, counts, waiting, size = np.empty(0, np.uint32), np.empty(0, np.int64), [], 0

    def merged() -> tuple[np.ndarray, np.ndarray]:
        k, c = np.unique(four_grams(waiting), return_counts=True)
        every, at = np.unique(np.concatenate([keys, k]), return_inverse=True)
        return every, np.bincount(at, np.concatenate([counts, c])).astype(np.int64)

    def out() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(keys.astype(np.int64)), pa.array(counts)], names=["gram", "c"])

    for b in sliced(batches):
        for t in _bytes(b.column(0)):
            if t:
                waiting.append(t)
                size += len(t)
            if size > 4 << 20:
                keys, counts = merged()
                waiting, size = [], 0
                if len(keys) > FLUSH:
                    yield out()
                    keys, counts = keys[:0], counts[:0]
    if waiting:
        keys, counts = merged()
    if len(keys):
        yield out()


# --- the folded trie ------------------------------------------------------------------------


def _open_sum(c: np.ndarray, excluded: np.ndarray) -> np.ndarray:
    """Log10 of n + d for rows of counts without the excluded symbols (0 where nothing is left)."""
    d = (c > 0).sum(-1)
    total = np.where(excluded, 0.0, c).sum(-1) + np.where(d < c.shape[-1], d, 0)
    with np.errstate(divide="ignore"):
        return np.where(total > 0, np.log10(total), 0.0)


class Lower:
    """Orders 0 to 2: ``table`` has, for a byte after two, log10 of its count if they have it,
    else of their escape and what the shorter contexts give it; ``whole`` is what a context of
    two subtracts when no longer one has excluded anything."""

    def __init__(self, low: np.ndarray, low_counts: np.ndarray):
        counts = np.zeros((256, 256, 256), np.float32)
        counts.reshape(-1)[low] = low_counts
        self.counts: np.ndarray | None = counts
        c1 = counts.sum(0, dtype=np.float64)
        c0 = c1.sum(0)
        d0 = (c0 > 0).sum()
        with np.errstate(divide="ignore"):
            p0 = np.where(c0 > 0, np.log10(c0), (math.log10(d0) if d0 else 0.0) - math.log10(max(1, 256 - d0)))
        p1, whole1 = self._order(c1, np.broadcast_to(c0, (256, 256)), p0, _open_sum(c0, np.zeros(256, bool)))
        self.table, self.whole = np.empty((256, 256, 256), np.float32), np.empty((256, 256))
        for first in range(256):
            self.table[first], self.whole[first] = self._order(counts[first].astype(np.float64), c1, p1, whole1)

    @staticmethod
    def _order(c: np.ndarray, shorter: np.ndarray, p: np.ndarray, whole: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows of contexts with counts ``c``; of each one's shorter context its counts, table and whole."""
        seen, d = c > 0, (c > 0).sum(-1)
        known = d > 0
        with np.errstate(divide="ignore", invalid="ignore"):
            escape = np.where(known, np.log10(d) - _open_sum(shorter, seen), -whole)
            return np.where(seen, np.log10(c), escape[:, None] + p), np.where(known, _open_sum(c, np.zeros(c.shape, bool)), 0.0)


class Trie:
    """Log10 probabilities of a fixed trie: a dense table of three bytes (two of context),
    and open-addressed tables for leaves and for escapes of four-byte contexts."""

    def __init__(self, grams: np.ndarray, counts: np.ndarray, low: np.ndarray, low_counts: np.ndarray):
        """grams: all four-byte numbers with counts; low: all three-byte numbers with counts."""
        self.lower, self.rare = Lower(low, low_counts), False
        own, used, escape, _ = leaf_terms(grams.astype(np.uint32), counts.astype(np.float64), self.lower.counts)
        self._fill(grams.astype(np.uint32), own, used, escape)

    @classmethod
    def of_terms(cls, lower: Lower, grams: np.ndarray, own: np.ndarray, used: np.ndarray, escape: np.ndarray, rare: bool) -> Trie:
        """From finished leaves (all or, if ``rare``, some) and the escapes of all contexts."""
        made = cls.__new__(cls)
        made.lower, made.rare = lower, rare
        made._fill(grams.astype(np.uint32), own, used.astype(np.uint32), escape)
        return made

    def _fill(self, grams: np.ndarray, own: np.ndarray, used: np.ndarray, escape: np.ndarray) -> None:
        self.leaf_keys, self.leaf_values = _table(grams, own)
        if len(used) <= 1 << 21:
            self.esc_keys, self.esc_values = _table(used, escape)
        else:  # a dense table is smaller
            self.esc_keys, self.esc_values = None, np.full(1 << 24, np.nan, np.float32)
            self.esc_values[used] = escape

    def score(self, text: bytes) -> float:
        """Log10 probability of the bytes (of a trie without rare leaves)."""
        return self.score_parts(text)[0]

    def score_at(self, context: bytes, byte: int) -> float:
        """Log10 probability of a byte after the last three bytes."""
        return float(self._of(np.array([int.from_bytes(context[-3:], "big") << 8 | byte], np.uint32))[0])

    def score_parts(self, text: bytes) -> tuple[float, list[int], list[int]]:
        """The score with all strings outside the leaves taken as unseen, and those of them
        that may be rare leaves (their context is known), with how often they occur."""
        if not text:
            return 0.0, [], []
        p, maybe = self._parts(four_grams([text]))
        missed, times = np.unique(maybe, return_counts=True) if self.rare else (maybe[:0], maybe[:0])
        return float(p.sum(dtype=np.float64)), missed.tolist(), times.tolist()

    def _of(self, grams: np.ndarray) -> np.ndarray:
        return self._parts(grams)[0]

    def _escapes(self, contexts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.esc_keys is not None:
            return _lookup(self.esc_keys, self.esc_values, contexts)
        got = self.esc_values[contexts]
        known = ~np.isnan(got)
        return np.where(known, got, np.float32(0)), known

    def _parts(self, grams: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        p, found = _lookup(self.leaf_keys, self.leaf_values, grams)
        missed = grams[~found]
        if len(missed):
            extra, known = self._escapes(missed >> np.uint32(8))
            whole = self.lower.whole.reshape(-1)[(missed >> np.uint32(8)) & np.uint32(0xFFFF)]
            p[~found] = np.where(known, extra, -whole) + self.lower.table.reshape(-1)[missed & np.uint32(0xFFFFFF)]
            missed = missed[known]
        return p, missed


def leaf_terms(grams: np.ndarray, counts: np.ndarray, low_counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of all strings of some contexts: their log probabilities; the contexts, what an escape
    adds to the entry of ``Lower.table``, and the place of each string's context."""
    used, at = np.unique(grams >> np.uint32(8), return_inverse=True)
    n, d = np.bincount(at, counts, len(used)), np.bincount(at, minlength=len(used))
    shorter, step = np.empty(len(used)), 4096
    order = np.argsort(at, kind="stable")
    ends = np.searchsorted(at[order], np.arange(0, len(used) + step, step))
    for i, (a, b) in enumerate(zip(ends, ends[1:], strict=False)):
        part, mine = used[i * step : (i + 1) * step], order[a:b]
        low = low_counts[(part >> np.uint32(8)) & np.uint32(255), part & np.uint32(255)].astype(np.float64)
        excluded = np.zeros(low.shape, bool)
        excluded[at[mine] - i * step, grams[mine] & np.uint32(255)] = True
        shorter[i * step : (i + 1) * step] = _open_sum(low, excluded)
    whole = n + np.where(d < 256, d, 0)
    return np.log10(counts / whole[at]), used, np.log10(d / whole) - shorter, at


_EMPTY = np.uint32(0xFFFFFFFF)


def _slots(keys: np.ndarray, bits: int) -> np.ndarray:
    return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - bits)).astype(np.int64)


def _table(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Open addressing with linear probing, filled in rounds."""
    bits = max(4, int(len(keys) * 3).bit_length())
    at, out, filled = _slots(keys, bits), np.zeros(1 << bits, np.float32), np.full(1 << bits, _EMPTY)
    todo = np.arange(len(keys))
    while len(todo):
        free = filled[at[todo]] == _EMPTY
        _, first = np.unique(at[todo[free]], return_index=True)
        won = todo[free][first]
        filled[at[won]], out[at[won]] = keys[won], values[won]
        todo = todo[filled[at[todo]] != keys[todo]]
        at[todo] = (at[todo] + 1) & ((1 << bits) - 1)
    return filled, out


def _lookup(filled: np.ndarray, values: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values (0 where absent) and whether each key is there."""
    bits = len(filled).bit_length() - 1
    at = _slots(keys, bits)
    got = filled[at]
    found = got == keys
    out = np.where(found, values[at], np.float32(0))
    todo = np.flatnonzero(~found & (got != _EMPTY))
    while len(todo):
        at[todo] = (at[todo] + 1) & (len(filled) - 1)
        got = filled[at[todo]]
        hit = got == keys[todo]
        out[todo[hit]], found[todo[hit]] = values[at[todo[hit]]], True
        todo = todo[~hit & (got != _EMPTY)]
    return out, found


def train(docs: DataFrame) -> DataFrame:
    """Counts of four-byte numbers over the texts (gram, c), parked."""
    return park(docs.select("text").mapInArrow(_gram_counts, "gram long, c long").groupBy("gram").agg(F.sum("c").alias("c")), "grams")


def _leaf_threshold(grams: DataFrame) -> int:
    """The least power of two such that at most 2 ** LEAF_BITS strings occur as often."""
    bits = {r.bits: r.n for r in grams.groupBy(F.length(F.bin("c")).alias("bits")).agg(F.count("*").alias("n")).collect()}
    kept, least = 0, max(bits, default=0) + 1
    while least > 1 and kept + bits.get(least - 1, 0) <= 1 << LEAF_BITS:
        least -= 1
        kept += bits.get(least, 0)
    return 1 << (least - 1)


def fold(grams: DataFrame) -> tuple[Trie, DataFrame | None]:
    """The trie as tables, and the leaves left out of it (gram, gain: what to add where the
    trie took the string as unseen), None if there are none. The driver gets at most
    2 ** LEAF_BITS leaves, the escapes and the three-byte counts (at most 2 ** 24 each)."""
    spark = grams.sparkSession
    column = lambda t, k: t.column(k).to_numpy()
    low = grams.groupBy((F.col("gram") % (1 << 24)).alias("gram")).agg(F.sum("c").alias("c")).toArrow()
    lower = Lower(column(low, "gram"), column(low, "c"))
    shared = spark.sparkContext.broadcast(lower)  # two tables of 2 ** 24 numbers

    def terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            got, c = (pa.concat_arrays([b.column(k)]).flatten().to_numpy() for k in (0, 1))
            if not len(got):
                continue
            keys = got.astype(np.uint32)
            own, used, escape, at = leaf_terms(keys, c.astype(np.float64), shared.value.counts)
            first = np.zeros(len(keys), bool)
            first[np.unique(at, return_index=True)[1]] = True
            gain = own - escape[at] - shared.value.table.reshape(-1)[keys & np.uint32(0xFFFFFF)]
            yield pa.RecordBatch.from_arrays([pa.array(got), pa.array(c), pa.array(own), pa.array(gain), pa.array(escape[at]), pa.array(first)], names=["gram", "c", "own", "gain", "escape", "first"])

    # the strings of one context, 256 at most, meet in a row
    whole = grams.groupBy(F.shiftright("gram", 8).alias("context")).agg(F.collect_list(F.struct("gram", "c")).alias("z")).select(F.col("z.gram").alias("gram"), F.col("z.c").alias("c"))
    leaves = park(whole.mapInArrow(terms, "gram long, c long, own double, gain double, escape double, first boolean"), "leaves")
    least = _leaf_threshold(leaves)
    often = leaves.where(F.col("c") >= least).select(F.col("gram"), F.col("own").cast("float")).toArrow()
    escapes = leaves.where("first").select(F.shiftright("gram", 8).cast("int").alias("context"), F.col("escape").cast("float")).toArrow()
    lower.counts = None  # scoring needs the table only
    trie = Trie.of_terms(lower, column(often, "gram"), column(often, "own"), column(escapes, "context"), column(escapes, "escape"), least > 1)
    shared.destroy()
    return trie, leaves.where(F.col("c") < least).select("gram", "gain") if least > 1 else None


# --- scoring --------------------------------------------------------------------------------


def score_texts(docs: DataFrame, fold_of: int = 10) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    training = docs.where(~held_out(F.col("doc_id"), fold_of))
    counts = park(training.select("text").mapInArrow(_word_counts, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c")), "words")
    n, v = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).head()
    scale = math.log10(n + 0.1 * (v + 1))
    often = F.col("c") >= max(1, math.ceil(n / (1 << WORD_BITS)))
    common = counts.where(often).toArrow()  # at most 2 ** WORD_BITS words
    logs = dict(zip(common.column("word").to_pylist(), (np.log10(common.column("c").to_numpy() + 0.1) - scale).tolist(), strict=True))
    trie, rare_leaves = fold(train(training))
    shared = spark.sparkContext.broadcast((trie, logs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie, logs = shared.value
        get = logs.get
        for b in sliced(batches):
            out = {k: [] for k in ("row", "n_tokens", "n_common", "base", "score", "rare", "times", "missed", "missed_times")}
            for text in _bytes(b.column(2)):
                per: dict = Counter(tokens(text))
                base, sure, rare, times = 0.0, 0, [], []
                for w, k in per.items():
                    x = get(w)
                    if x is None:
                        rare.append(w)
                        times.append(k)
                    else:
                        base += k * x
                        sure += k
                score, missed, missed_times = trie.score_parts(text)
                for k, x in zip(out, (0, sum(per.values()), sure, base, score, rare, times, missed, missed_times), strict=True):
                    out[k].append(x)
            longs = pa.int64()
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out["n_tokens"], longs), pa.array(out["n_common"], longs), pa.array(out["base"], pa.float64()), pa.array(out["score"], pa.float64()), pa.array(out["rare"], pa.list_(pa.binary())), pa.array(out["times"], pa.list_(longs)), pa.array(out["missed"], pa.list_(longs)), pa.array(out["missed_times"], pa.list_(longs))], names=["row", "doc_id", "n_tokens", "n_common", "base", "score", "rare", "times", "missed", "missed_times"])

    numbered = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    scored = park(numbered.mapInArrow(run, "row long, doc_id long, n_tokens long, n_common long, base double, score double, rare array<binary>, times array<long>, missed array<long>, missed_times array<long>"), "scored")
    rare_words = counts.where(~often)
    asked = scored.select("row", F.explode(F.arrays_zip("rare", "times")).alias("z")).select("row", F.col("z.rare").alias("word"), F.col("z.times").alias("k"))
    # words that training lacks score as c = 0: only those found are corrected
    zero = math.log10(0.1)
    found = asked.join(rare_words, "word").groupBy("row").agg(F.sum("k").alias("n_found"), F.sum(F.col("k") * (F.log10(F.col("c") + 0.1) - zero)).alias("gain"))
    n_rare = F.col("n_tokens") - F.col("n_common")
    out = scored.select("row", "doc_id", "n_tokens", "n_common", "base", "score").join(found, "row", "left")
    score = F.col("score")
    if rare_leaves is not None:
        # strings that training lacks stay as scored: only those found are corrected
        unsure = scored.select("row", F.explode(F.arrays_zip("missed", "missed_times")).alias("z")).select("row", F.col("z.missed").alias("gram"), F.col("z.missed_times").alias("k"))
        gains = unsure.join(rare_leaves, "gram").groupBy("row").agg(F.sum(F.col("k") * F.col("gain")).alias("leaf_gain"))
        out = out.join(gains, "row", "left")
        score = score + F.coalesce("leaf_gain", F.lit(0.0))
    return out.select("doc_id", held_out(F.col("doc_id"), fold_of).alias("held_out"), "n_tokens", (F.col("n_common") + F.coalesce("n_found", F.lit(0))).alias("n_known"), F.lit(n).cast("long").alias("train_tokens"), (F.col("base") + n_rare * (zero - scale) + F.coalesce("gain", F.lit(0.0))).alias("base_score"), score.alias("score"))


# --- adaptive form ---------------------------------------------------------------------------


def score_adaptive(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """doc_id and score: each text's log10 probability under a trie that starts empty and
    learns the text as it codes it; null is the empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([adaptive_score(t, order) for t in _bytes(b.column(1))], pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")


def adaptive_score(text: bytes, order: int = ORDER, primer: bytes = b"") -> float:
    """Log10 probability of a text whose trie learns as it goes (after a primer, if given)."""
    trie: dict[bytes, Counter] = {}
    total, past = 0.0, b""
    for place, b in enumerate(primer + text):
        log, excluded = 0.0, set()
        for k in range(min(order, len(past)), -1, -1):
            node = trie.get(past[len(past) - k :])
            if not node:
                continue
            left = {s: c for s, c in node.items() if s not in excluded}
            if not left:
                continue
            n, d = sum(left.values()), len(node)
            if len(excluded) + len(left) == 256:
                d = 0
            if b in left:
                log += math.log10(left[b] / (n + d))
                break
            log += math.log10(d / (n + d))
            excluded |= left.keys()
        else:
            log -= math.log10(256 - len(excluded))
        if place >= len(primer):
            total += log
        for k in range(min(order, len(past)) + 1):
            trie.setdefault(past[len(past) - k :], Counter())[b] += 1
        past = (past + bytes([b]))[-order:] if order else b""
    return total
