"""Near-duplicate classes by an inverted join over signature coordinates.

Each text becomes a set of five-word shingles (64-bit hashes of words, ASCII
lower case) and a MinHash signature. A coordinate combines ``ROWS`` minhashes,
so that a passage which many documents share makes no long posting lists.
Documents with equal sets are one class and post once, under each of
``COORDINATES`` coordinate-value pairs. Pairs that collide in ``MIN_MATCHES``
lists or more are confirmed on full shingle sets. Lists of one are dropped, and
documents with fewer than ``MIN_MATCHES`` lists left. No list is capped.

1. Prefix merging: every document meets the smallest document of all its lists.
   Their collisions are counted by merging postings: it is first in each list
   they share. What that leaves in another component meets the first, then the
   last document of each list.
2. Skip merging: lists whose members are still in several components are open. A
   pair to be found has ``MIN_MATCHES`` open lists in common, so all but the
   ``MIN_MATCHES`` - 1 longest open lists of each document are merged; those
   are skipped and only probed, when a pair's collisions are counted. Long lists
   fall into cells of at most ``CELL`` by ``CELL`` members, so no task
   holds a list. A cell gives only pairs of different components whose sizes and
   distances to the documents met in 1. (Jaccard distance is a metric) leave
   them open.

A pair collides in at least three of 40 coordinates of 6 minhashes
but for 2e-6 at similarity 0.85 (6e-4 at 0.8). Before any text moves, sketches
are compared. A sketch keeps the smallest
shingle of each of ``BINS`` bins as four bits; a pair is left out where its equal
bins are ``SPREAD`` standard deviations below what the similarity asked for
gives (about 2e-6 again). Sets that are small beside the bins hardly lose
shingles in them, so there the test comes close to the full sets.

Defined results: null text and texts without words have no shingles and no
link; fewer than five words make one shingle; rows with a null id get no
component and stay; rows that share an id are one document with several texts;
an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import drop, maybe_in, park, sliced

SHINGLE, ROWS, COORDINATES, MIN_MATCHES = 5, 6, 40, 3
BINS, PLANES, SPREAD, CELL = 1024, 4, 4.6, 256
_LONGS = BINS // 64
_ODD = np.uint64(0x9E3779B97F4A7C15)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_FOLD = np.arange(256, dtype=np.uint64) + np.uint64(1)
_FOLD[65:91] += np.uint64(32)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _Powers:
    """Powers of an odd number modulo 2**64, and of its inverse, as long as needed."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def reach(self, n: int) -> None:
        if len(self.up) < n:
            n, inverse = max(n, 1 << 14), np.uint64(pow(int(_ODD), -1, 1 << 64))
            with np.errstate(over="ignore"):
                self.up = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n - 1, _ODD)]), dtype=np.uint64)
                self.down = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n - 1, inverse)]), dtype=np.uint64)


_powers = _Powers()


def shingles(text: bytes) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's five-word shingles."""
    raw = np.frombuffer(text, np.uint8)
    gap = _SPACE[raw]
    edge = np.flatnonzero(np.diff(gap, prepend=True, append=True))
    starts, ends = edge[::2], edge[1::2]
    if not len(starts):
        return np.empty(0, np.uint64)
    _powers.reach(len(raw) + 1)
    sums = np.empty(len(raw) + 1, np.uint64)
    sums[0] = 0
    np.cumsum(_FOLD[raw] * _powers.up[: len(raw)], out=sums[1:])
    w = mix64((sums[ends] - sums[starts]) * _powers.down[starts] + (ends - starts).astype(np.uint64))
    if len(w) < SHINGLE:
        out = np.uint64(len(w))
        for x in w:
            out = mix64(np.array([out * _ODD + x]))[0]
        return np.array([out])
    h = w[: len(w) - SHINGLE + 1].copy()
    for k in range(1, SHINGLE):
        h = mix64(h) + w[k : len(w) - SHINGLE + 1 + k]
    return np.unique(mix64(h))


_rng = np.random.default_rng(20_240)
_SEEDS = _rng.integers(0, 1 << 32, ROWS * COORDINATES, dtype=np.uint32)
_MULT = _rng.integers(0, 1 << 31, ROWS * COORDINATES, dtype=np.uint32) * np.uint32(2) + np.uint32(1)


def coordinates(h: np.ndarray) -> np.ndarray:
    """The signature: for each coordinate one value of its minhashes and its number."""
    low = np.full(ROWS * COORDINATES, np.uint32(0xFFFFFFFF))
    x = (h >> np.uint64(32)).astype(np.uint32)
    for i in range(0, len(x), 512):
        y = x[None, i : i + 512] ^ _SEEDS[:, None]
        y *= _MULT[:, None]
        np.minimum(low, y.min(axis=1), out=low)
    out = np.arange(COORDINATES, dtype=np.uint64)
    for r in range(ROWS):
        out = mix64(out * _ODD + low[r::ROWS].astype(np.uint64))
    return out.view(np.int64)


def sketch(h: np.ndarray) -> np.ndarray:
    """Bit planes over the bins: which hold a shingle of the sorted set ``h``, then bits of the smallest."""
    bins = h >> np.uint64(64 - BINS.bit_length() + 1)
    least = np.flatnonzero(np.diff(bins, prepend=~bins[:1]))
    marks = mix64(h[least] ^ _ODD)
    bits = np.zeros((1 + PLANES, BINS), bool)
    bits[0, bins[least]] = True
    for k in range(PLANES):
        bits[1 + k, bins[least]] = marks >> np.uint64(k) & np.uint64(1)
    return np.packbits(bits).view(np.int64)


def alike(sizes: np.ndarray, planes: np.ndarray, sizes2: np.ndarray, planes2: np.ndarray, percent: int) -> np.ndarray:
    """Whether the sketches of pairs (set sizes, rows of bit planes) leave their similarity open."""
    p, q = (x.view(np.uint64).reshape(len(x), 1 + PLANES, _LONGS) for x in (planes, planes2))
    unlike = np.bitwise_or.reduce(p[:, 1:] ^ q[:, 1:], axis=1)
    equal = np.bitwise_count(p[:, 0] & q[:, 0] & ~unlike).sum(1, dtype=np.int64)
    held = np.bitwise_count(p[:, 0] | q[:, 0]).sum(1, dtype=np.int64)
    asked = percent / 100
    # bins draw from the union without putting back; of a pair to keep it has at most so many
    union = (sizes + sizes2) / (1 + asked)
    spread = np.sqrt(asked * (1 - asked) * held * np.maximum(union - held, 0.0) / np.maximum(union - 1, 1.0))
    return equal + 1 >= asked * held - SPREAD * spread


def _lists(column: pa.Array, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), width)


def _screen(percent: int):
    """Of pairs (a, b) with both documents' marks, those that collide and look near enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, 4096):
            c, d = (_lists(b.column(k), COORDINATES) for k in ("ca", "cb"))
            near = (c == d).sum(1) >= MIN_MATCHES
            n, m = (b.column(k).to_numpy() for k in ("na", "nb"))
            near &= 100 * np.minimum(n, m) >= percent * np.maximum(n, m)
            near &= alike(n, _lists(b.column("pa"), (1 + PLANES) * _LONGS), m, _lists(b.column("pb"), (1 + PLANES) * _LONGS), percent)
            yield b.select(["a", "b"]).filter(pa.array(near))

    return run


def _cells(percent: int):
    """Pairs (a, b) within cells: rows sorted by cell, of at most twice ``CELL`` members each."""
    near = 1 - percent / 100 + 1e-9
    keys = ("v", "i", "j")

    def met(rows: pa.Table) -> pa.RecordBatch:
        get = lambda k: rows.column(k).to_numpy()
        part = lambda k, width: np.concatenate([_lists(x, width) for x in rows.column(k).chunks])
        x, label, size, pivot, chunk = map(get, ("x", "label", "size", "pivot", "chunk"))
        same = get("i")[0] == get("j")[0]
        left = np.flatnonzero(chunk == get("i")[0])
        right = left if same else np.flatnonzero(chunk != get("i")[0])
        p, q = left[:, None], right[None, :]
        ok = label[p] != label[q]
        ok &= 100 * np.minimum(size[p], size[q]) >= percent * np.maximum(size[p], size[q])
        for k in ("d0", "d1", "d2"):
            d = get(k)
            with np.errstate(invalid="ignore"):
                apart = np.abs(d[p] - d[q]) > near  # false where a distance isn't known
            ok &= ~(apart & (pivot[p] == pivot[q])) if k == "d0" else ~apart
        if same:
            ok &= x[p] < x[q]
        r, c = np.nonzero(ok)
        a, b = left[r], right[c]
        coords, planes = part("coords", COORDINATES), part("planes", (1 + PLANES) * _LONGS)
        kept = []
        for k in range(0, len(a), 1 << 14):
            f, g = a[k : k + (1 << 14)], b[k : k + (1 << 14)]
            good = (coords[f] == coords[g]).sum(1) >= MIN_MATCHES
            f, g = f[good], g[good]
            good = alike(size[f], planes[f], size[g], planes[g], percent)
            kept.append((f[good], g[good]))
        a, b = (np.concatenate([z[k] for z in kept]) if kept else np.empty(0, np.int64) for k in (0, 1))
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(x[a], x[b])), pa.array(np.maximum(x[a], x[b]))], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in sliced(batches, 2048):
            cols = [batch.column(k).to_numpy() for k in keys]
            cut = np.flatnonzero(np.any([np.diff(c) != 0 for c in cols], axis=0)) + 1
            edges = [0, *cut.tolist(), len(batch)]
            first = tuple(c[0] for c in cols)
            if held and tuple(held[0].column(k)[0].as_py() for k in keys) != first:
                yield met(pa.Table.from_batches(held))
                held = []
            for s, e in zip(edges, edges[1:], strict=False):
                held.append(batch.slice(s, e - s))
                if e < len(batch):
                    if sum(map(len, held)) > 1:
                        yield met(pa.Table.from_batches(held))
                    held = []
        if held:
            yield met(pa.Table.from_batches(held))

    return run


def _sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    with np.errstate(over="ignore"):
        for b in sliced(batches):
            sets = [shingles(t) for t in _bytes(b.column(1))]
            flat = np.concatenate([sketch(h) for h in sets])
            offsets = np.arange(len(sets) + 1, dtype=np.int32) * np.int32((1 + PLANES) * _LONGS)
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array([len(h) for h in sets], pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], names=["x", "size", "planes"])


def _bytes(column: pa.Array) -> list[bytes]:
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def _signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    with np.errstate(over="ignore"):
        for b in sliced(batches):
            n, one, two, sig = [], [], [], []
            for text in _bytes(b.column(1)):
                h = shingles(text)
                n.append(len(h))
                one.append(int(h.sum(dtype=np.uint64).view(np.int64)) if len(h) else 0)
                two.append(int(mix64(h ^ _ODD).sum(dtype=np.uint64).view(np.int64)) if len(h) else 0)
                sig.append(coordinates(h) if len(h) else np.empty(0, np.int64))
            offsets = np.concatenate([[0], np.cumsum([len(s) for s in sig])]).astype(np.int32)
            values = np.concatenate(sig) if sig else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(one, pa.int64()), pa.array(two, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values))], names=["doc_id", "n_shingles", "one", "two", "coords"])


SIGNED = "doc_id long, n_shingles long, one long, two long, coords array<long>"


def _compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    last, a_set = None, None
    with np.errstate(over="ignore"):
        for b in sliced(batches, 256):
            out = []
            for left, right in zip(_bytes(b.column(2)), _bytes(b.column(3)), strict=True):
                if left != last:
                    last, a_set = left, shingles(left)
                b_set = shingles(right)
                both = len(np.intersect1d(a_set, b_set, assume_unique=True))
                out.append((both, len(a_set) + len(b_set) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64())], names=["a", "b", "both", "either"])


def confirm(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """a, b, both, either (sizes of intersection and union of full shingle sets) for pairs."""
    of = lambda x: texts.select(F.col("doc_id").alias(x), F.col("text").alias(f"t{x}"))
    joined = pairs.join(of("b").hint("merge"), "b").join(of("a").hint("merge"), "a").select("a", "b", "ta", "tb")
    found = joined.mapInArrow(_compared, "a long, b long, both long, either long")
    # rows that share an id give several; the closest counts
    return found.groupBy("a", "b").agg(F.max_by(F.struct("both", "either"), F.col("both") / F.col("either")).alias("s")).select("a", "b", "s.both", "s.either")


def components(edges: DataFrame) -> DataFrame:
    """node, label (smallest node reachable) for undirected edges (a, b), parked."""
    both = park(edges.select("a", "b").union(edges.select("b", "a")).toDF("u", "v").distinct(), "edges")
    labels = park(both.groupBy("u").agg(F.least(F.first("u"), F.min("v")).alias("label")), "labels")
    while True:
        lower = both.join(labels.select(F.col("u").alias("v"), "label"), "v").groupBy("u").agg(F.min("label").alias("low"))
        met = labels.join(lower, "u").select("u", F.col("label").alias("old"), F.least("label", "low").alias("mid"))
        jump = labels.select(F.col("u").alias("mid"), F.col("label").alias("far"))
        new = park(met.join(jump, "mid", "left").select("u", "old", F.least("mid", F.coalesce("far", "mid")).alias("label")), "labels")
        changed = new.where("old <> label").limit(1).count()
        drop(labels)
        labels = new
        if not changed:
            drop(both)
            out = labels.select(F.col("u").alias("node"), "label")
            out.parked_at = labels.parked_at
            return out


def near_classes(docs: DataFrame, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id and kept, one row per input row.

    Joins on many rows are merge joins at every size, so that what is moved grows as the input does.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sigs = park(docs.mapInArrow(_signed, SIGNED), "signatures")
    known = sigs.where("doc_id is not null and n_shingles > 0")
    classes = known.groupBy("n_shingles", "one", "two").agg(F.min("doc_id").alias("rep"))
    heads = classes.select("rep").distinct().hint("merge")
    signed = park(known.join(heads, known["doc_id"] == F.col("rep"), "left_semi").select(F.col("doc_id").alias("x"), "coords"), "posters")
    posted = signed.select(F.explode("coords").alias("v"), "x")
    lists = posted.groupBy("v").agg(F.min("x").alias("first"), F.max("x").alias("last")).where("first <> last")
    shared = park(posted.join(lists.hint("merge"), "v"), "shared")
    pivots = park(shared.groupBy("x").agg(F.min("first").alias("pivot"), F.count("*").alias("n")).where(f"n >= {MIN_MATCHES}"), "pivots")
    members = park(shared.join(pivots.hint("merge"), "x"), "members")
    ids = members.select("x").distinct()
    # a bounded filter first: most texts and signatures need not move
    some = lambda df, key: maybe_in(df, key, ids, "_some").where("_some").drop("_some").join(ids.withColumnRenamed("x", key).hint("merge"), key, "left_semi")
    texts = park(some(docs, "doc_id").select("doc_id", "text"), "texts")
    sketches = texts.mapInArrow(_sketched, "x long, size long, planes array<long>")
    marks = park(some(signed, "x").join(sketches.hint("merge"), "x").select("x", "size", "coords", "planes"), "marks")
    linked = f"100 * both >= {percent} * either"

    def tested(pairs: DataFrame) -> DataFrame:
        side = lambda k: marks.toDF(k, f"n{k}", f"c{k}", f"p{k}").hint("merge")
        seen = pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "na", "nb", "ca", "cb", "pa", "pb")
        near = park(seen.mapInArrow(_screen(percent), "a long, b long").distinct(), "near")
        out = park(confirm(near, texts), "tested")
        drop(near)
        return out

    def labelled(rows: DataFrame, comp: DataFrame, node: str, name: str) -> DataFrame:
        found = comp.select(F.col("node").alias(node), F.col("label").alias(name))
        return rows.join(found, node, "left").withColumn(name, F.coalesce(name, node))

    # prefix merging: a pivot is first in all lists that it shares, so merging counts whole collisions
    firsts = members.where("first = pivot and x <> pivot").groupBy("pivot", "x").count().where(f"count >= {MIN_MATCHES}")
    tried = tested(firsts.select(F.col("pivot").alias("a"), F.col("x").alias("b")))
    comp = components(tried.where(linked))
    for center in ("first", "last"):
        rest = labelled(labelled(members.where(F.col("x") != F.col(center)), comp, "x", "lx"), comp, center, "lc").where("lx <> lc")
        rest = rest.select(F.least("x", center).alias("a"), F.greatest("x", center).alias("b")).distinct().join(tried, ["a", "b"], "left_anti")
        more = tested(rest)
        both = park(tried.union(more), "tried")
        drop(tried, more, comp)
        tried = both
        comp = components(tried.where(linked))
    # skip merging: lists whose members are still in several components
    open_of = lambda rows: rows.groupBy("v").agg(F.min("label").alias("low"), F.max("label").alias("high"), F.count("*").alias("n")).where("low <> high").select("v", "n")
    left = labelled(members.select("v", "x", "pivot", "first", "last"), comp, "x", "label")
    left = park(left.join(open_of(left), "v"), "left")
    mine = Window.partitionBy("x")
    ranked = left.withColumn("m", F.count("*").over(mine)).withColumn("r", F.row_number().over(mine.orderBy("n", "v")))
    merged = park(ranked.where(f"r <= m - {MIN_MATCHES - 1}").drop("m", "r", "n"), "merged")
    far = tried.select("a", "b", (1 - F.col("both") / F.col("either")).alias("d"))
    ways = far.union(far.select("b", "a", "d")).toDF("center", "x", "d")
    rows = merged.join(open_of(merged), "v")
    for center, name in (("pivot", "d0"), ("first", "d1"), ("last", "d2")):
        rows = rows.join(ways.toDF(center, "x", name), [center, "x"], "left")
        rows = rows.withColumn(name, F.when(F.col("x") == F.col(center), 0.0).otherwise(F.col(name)))
    rows = rows.withColumn("k", F.ceil(F.col("n") / CELL).cast("int")).withColumn("chunk", F.pmod(F.xxhash64("x"), F.col("k")).cast("int"))
    rows = rows.join(marks.hint("merge"), "x").select("v", "x", "label", "pivot", "d0", "d1", "d2", "k", "chunk", "size", "coords", "planes")
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    celled = rows.select("v", F.least("chunk", "other").alias("i"), F.greatest("chunk", "other").alias("j"), "chunk", "x", "label", "pivot", "size", "d0", "d1", "d2", "coords", "planes")
    celled = celled.repartition("v", "i", "j").sortWithinPartitions("v", "i", "j")
    found = park(celled.mapInArrow(_cells(percent), "a long, b long").distinct().join(tried, ["a", "b"], "left_anti"), "found")
    if found.limit(1).count():
        drop(comp)
        more = park(confirm(found, texts), "tested")
        comp = components(tried.union(more).where(linked))
        drop(more)
    by_class = park(classes.join(comp, classes["rep"] == comp["node"], "left").select("n_shingles", "one", "two", F.coalesce("label", "rep").alias("component")), "classes")
    drop(signed, shared, pivots, members, texts, marks, tried, left, merged, found, comp)
    out = sigs.select("doc_id", "n_shingles", "one", "two").join(by_class, ["n_shingles", "one", "two"], "left")
    component = F.when((F.col("n_shingles") == 0) | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.col("component"))
    return out.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, percent: int = 80) -> DataFrame:
    """``docs`` with one document of each near-duplicate class (the smallest id; of rows that
    share that id, one). Rows without id stay."""
    judged = near_classes(docs, percent).where("doc_id is not null")
    odd = judged.groupBy("doc_id").agg(F.bool_or("kept").alias("stays"), (F.count("*") > 1).alias("several")).where("not stays or several")
    odd = park(odd.withColumnRenamed("doc_id", "odd_id"), "odd")
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col("doc_id").cast("long").alias("id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("t"))
    rows = maybe_in(rows, "id", odd.select("odd_id"), "open")
    met = rows.where("open").join(odd.hint("merge"), F.col("id") == F.col("odd_id"), "left")
    out = rows.where("not open").select("row").union(met.where("odd_id is null").select("row"))
    if odd.where("stays and several").limit(1).count():
        out = out.union(met.where("stays and several").groupBy("id").agg(F.min_by("row", "t").alias("row")).select("row"))
    return out.select("row.*")
