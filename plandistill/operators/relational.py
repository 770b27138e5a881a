"""Operators that a user of the methods needs beside plain SQL: as-of join, and the Python kinds."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType

from ..plans.complexity import by_text, structure
from .student import EarlyStop


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str, name: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before each row, of the same ``by``.

    Both sides go through one sort as one table, so a row never meets all earlier ones; at equal
    times the right side counts as earlier, and the largest value of a time is taken. Null keys
    or times match nothing."""
    sides = left.select(F.struct(*left.columns).alias("_row"), F.col(by).alias("_by"), F.col(on).alias("_on"), F.lit(1).alias("_side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("_value"))
    other = right.where(F.col(by).isNotNull() & F.col(on).isNotNull()).select(F.lit(None).cast(sides.schema["_row"].dataType).alias("_row"), F.col(by).alias("_by"), F.col(on).alias("_on"), F.lit(0).alias("_side"), F.col(value).alias("_value"))
    upto = Window.partitionBy("_by").orderBy("_on", "_side", "_value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    met = sides.union(other).withColumn("_last", F.last(F.when(F.col("_side") == 0, F.col("_value")), ignorenulls=True).over(upto)).where("_side = 1")
    known = F.col("_by").isNotNull() & F.col("_on").isNotNull()
    return met.select("_row.*", F.when(known, F.col("_last")).alias(name))


def first_max_by(value: Column, order: Column) -> Column:
    """The whole number ``value`` of the largest ``order``, the smallest one if several rows have
    it; rows where either is null don't count."""
    return F.max_by(value, F.when(value.isNotNull() & order.isNotNull(), F.struct(order.alias("o"), F.bitwise_not(value).alias("v"))))


def near_pairs(rows: DataFrame, by: str, key: str, near: str, within: float) -> DataFrame:
    """Pairs (x, y), x < y by ``key``, of the same ``by`` whose ``near`` differ by less than ``within``.

    Rows meet in cells of a power of two at least ``within`` wide, so division is exact and such
    rows lie in the same cell or in adjacent ones. Each pair is looked at from its lower cell
    alone. Nulls, NaN and infinities are near nothing. The join is by sort: a small input grows
    into many pairs, which should not be left to the few tasks that read it."""
    width = 2.0 ** math.ceil(math.log2(within))
    far = float(1 << 62)  # doubles beyond differ by more than a cell unless equal
    cell = F.floor(F.least(F.greatest(F.col(near) / width, F.lit(-far)), F.lit(far)))
    some = rows.where(F.abs(near) < float("inf")).select(F.col(by).alias("_by"), F.col(key).alias("_key"), F.col(near).alias("_near"), cell.alias("_cell"))
    low, high = some.alias("a"), some.withColumn("_meet", F.explode(F.array(F.col("_cell"), F.col("_cell") - 1))).alias("b")
    once = F.when(F.col("a._cell") == F.col("b._cell"), F.col("a._key") < F.col("b._key")).otherwise(F.col("a._key") != F.col("b._key"))
    met = low.join(high.hint("merge"), (F.col("a._by") == F.col("b._by")) & (F.col("a._cell") == F.col("b._meet")) & (F.abs(F.col("a._near") - F.col("b._near")) < within) & once)
    return met.select(F.least("a._key", "b._key").alias("x"), F.greatest("a._key", "b._key").alias("y"))


@F.udf(IntegerType())
def mark_count(text: str | None) -> int:
    """Row-at-a-time kind, for comparison: question marks in a text."""
    return (text or "").count("?")


@F.pandas_udf(IntegerType())
def keyword_count(sql: pd.Series) -> pd.Series:
    """Arrow-batched kind: constructs of a query by the lexer."""
    return by_text(sql.fillna(""), lambda x: len(structure(x))).astype("int32")


@F.pandas_udf(DoubleType())
def mean_gap(loss: pd.Series) -> float:
    """Grouped-aggregate kind: mean fall of a curve from its first value."""
    return float((loss.iloc[0] - loss).mean()) if len(loss) else 0.0


def longest_word(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """mapInPandas: key and the length of each text's longest word."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield pd.DataFrame({key: f[key], "longest": [max(map(len, (t or "").split()), default=0) for t in f[text]]})

    return docs.select(key, text).mapInPandas(run, f"{key} long, longest long")


def early_stop_by_loop(curves: DataFrame, patience: int = 8, tol: float = 1e-3) -> DataFrame:
    """applyInPandas: the loop form of early stopping, a run to a group; equals the window form."""

    def one(f: pd.DataFrame) -> pd.DataFrame:
        rule, best = EarlyStop(patience, tol), None
        for step, loss in f.sort_values("step")[["step", "loss"]].itertuples(index=False):
            if rule.better(loss):
                best = step
            if rule.done:
                break
        return pd.DataFrame({"run": [f["run"].iloc[0]], "stop_step": [step], "best_step": [best]})

    return curves.select("run", "step", "loss").groupBy("run").applyInPandas(one, "run long, stop_step int, best_step int")


def norm(x: Column) -> Column:
    return F.sqrt(F.aggregate(F.transform(x, lambda v: v.cast("double") * v.cast("double")), F.lit(0.0), lambda a, v: a + v))
