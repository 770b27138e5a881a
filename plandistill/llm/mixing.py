"""Mixing sources to target weights by capped water-filling (built-in functions only).

Targets share the total size by weight; a source whose share passes
``max_epochs`` times its own size is clamped there and what it can't take is
shared again by weight among the others, until none is above. A target is met
by whole repetitions of the source plus a seeded fraction: documents in the
order of a hash of their id up to the words that are missing. The cut inside a
source is found from word sums of hash buckets, then inside one bucket, so no
task sees a whole source.

Defined results: null text has size 0; null source is a source of its own,
last; more than ``MOST_SOURCES`` sources raise; rows with one id are told apart by a hash of their text (equal rows are
taken alike); an empty table gives no rows; other columns are carried in ``row``.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import n_words, park

BUCKETS = 1 << 10
#: Sources come to the driver and go out to all tasks, so their number is checked.
MOST_SOURCES = 1 << 18


def water_fill(sizes: dict[str, int], weights: dict[str, int], max_epochs: int, total: int | None = None) -> dict[str, Fraction]:
    """Targets as exact fractions. ``sizes`` has one entry for each source."""
    total = sum(sizes.values()) if total is None else total
    clamped: dict[str, Fraction] = {}
    while True:
        free = [s for s in sizes if s not in clamped]
        left, weight = Fraction(total) - sum(clamped.values()), sum(weights[s] for s in free)
        share = {s: left * weights[s] / weight for s in free} if weight else {}
        over = [s for s in free if share[s] > max_epochs * sizes[s]]
        if not over:
            return clamped | share
        clamped |= {s: Fraction(max_epochs * sizes[s]) for s in over}


def _sized(docs: DataFrame, seed: int, id_col: str) -> DataFrame:
    size = n_words(F.col("text"))
    return docs.select(F.col(id_col).alias("_id"), F.col("source").alias("_source"), size.alias("_size"), F.xxhash64(F.lit(seed), F.col(id_col)).alias("_rank"), F.xxhash64("text").alias("_tie"))


def _bucket() -> Column:
    return F.shiftrightunsigned(F.col("_rank"), 64 - BUCKETS.bit_length() + 1).cast("int")


def _limits(sized: DataFrame, weights: tuple[int, ...], max_epochs: int) -> DataFrame:
    """For each source: size, target, whole repetitions, and the place in hash order
    up to which documents are taken once more. One row for each source reaches the driver."""
    spark = sized.sparkSession
    found = sized.groupBy("_source").agg(F.sum("_size").alias("size")).limit(MOST_SOURCES + 1).collect()
    if len(found) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources: their targets are one table that every task holds; group them first")
    sizes = {r[0]: r[1] for r in found}
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    targets = water_fill(sizes, {s: weights[i % len(weights)] for i, s in enumerate(names)}, max_epochs)
    rows = []
    for s in names:
        whole = int(targets[s] // sizes[s]) if sizes[s] else 0
        rows.append((s, sizes[s], float(targets[s]), whole, float(targets[s] - whole * sizes[s])))
    plan = spark.createDataFrame(rows, "_source string, _source_size long, _target double, _whole int, _rest double")
    # first the bucket in which the missing words are reached, then the row inside it
    sums = sized.groupBy("_source", _bucket().alias("_bucket")).agg(F.sum("_size").alias("_n"))
    earlier = Window.partitionBy("_source").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    placed = sums.withColumn("_before", F.coalesce(F.sum("_n").over(earlier), F.lit(0)))
    cut = placed.join(F.broadcast(plan), placed["_source"].eqNullSafe(plan["_source"])).where((F.col("_before") < F.col("_rest")) & (F.col("_before") + F.col("_n") >= F.col("_rest")))
    cut = park(cut.select(placed["_source"].alias("_cs"), F.col("_bucket").alias("_cb"), F.col("_before").alias("_cbefore"), F.col("_rest").alias("_crest")), "cuts")
    inside = sized.withColumn("_bucket", _bucket())
    inside = inside.join(F.broadcast(cut), inside["_source"].eqNullSafe(cut["_cs"]) & (F.col("_bucket") == F.col("_cb")))
    so_far = Window.partitionBy("_cs").orderBy("_rank", "_tie", "_size").rowsBetween(Window.unboundedPreceding, 0)
    reached = inside.withColumn("_upto", F.col("_cbefore") + F.sum("_size").over(so_far))
    # the row that crosses the line is in if that ends nearer to the target
    start = F.col("_upto") - F.col("_size")
    nearer = F.col("_upto") - F.col("_crest") <= F.col("_crest") - start
    last = reached.where((F.col("_upto") <= F.col("_crest")) | ((start < F.col("_crest")) & nearer)).groupBy(F.col("_cs").alias("_ls")).agg(F.max(F.struct("_rank", "_tie")).alias("_edge"))
    edges = cut.join(last, F.col("_cs").eqNullSafe(F.col("_ls")), "left").select("_cs", "_cb", "_edge")
    return park(plan.join(edges, F.col("_source").eqNullSafe(F.col("_cs")), "left").select(F.col("_source").alias("_ps"), "_source_size", "_target", "_whole", "_rest", "_cb", "_edge"), "limits")


def _judged(rows: DataFrame, limits: DataFrame, source: str) -> DataFrame:
    inside = (F.col("_bucket") == F.col("_cb")) & F.coalesce(F.struct("_rank", "_tie") <= F.col("_edge"), F.lit(False))
    extra = (F.col("_rest") > 0) & ((F.col("_bucket") < F.col("_cb")) | inside)
    joined = rows.withColumn("_bucket", _bucket()).join(F.broadcast(limits), rows[source].eqNullSafe(F.col("_ps")))
    return joined.withColumn("copies", F.col("_whole") + F.coalesce(extra, F.lit(False)).cast("int"))


def mix_sizes(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), max_epochs: int = 3, seed: int = 7, id_col: str = "doc_id") -> DataFrame:
    """Per row: id, size, source_size, target and copies, without the texts (read once)."""
    sized = park(_sized(docs, seed, id_col), "sizes")
    out = _judged(sized, _limits(sized, weights, max_epochs), "_source")
    return out.select(F.col("_id").alias(id_col), F.col("_size").alias("size"), F.col("_source_size").alias("source_size"), F.col("_target").alias("target"), "copies")


def mix(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), max_epochs: int = 3, seed: int = 7, id_col: str = "doc_id") -> DataFrame:
    """row (a struct of all columns, so that no name clashes) and copies: how often the mix takes it."""
    limits = _limits(park(_sized(docs, seed, id_col), "sizes"), weights, max_epochs)
    ranked = docs.select(F.struct(*docs.columns).alias("row"), F.col("source").alias("_source"), F.xxhash64(F.lit(seed), F.col(id_col)).alias("_rank"), F.xxhash64("text").alias("_tie"))
    return _judged(ranked, limits, "_source").select("row", "copies")


def repeat(mixed: DataFrame) -> DataFrame:
    """One row for each time the mix takes a document; those it takes never are gone."""
    return mixed.where("copies > 0").select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")
