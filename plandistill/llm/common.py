"""Helpers shared by the corpus operators: scratch tables, batch limits, words."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes that part words, as a Java / DuckDB character class.
SPACES = " \t\n\x0b\x0c\r"
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def read(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The named columns of one table; only Spark's reader touches the path."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; a local one only where none is configured and the
    master is local, so that no other machine has to see it."""
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if not configured:
        found = spark.sparkContext.getCheckpointDir()
        if found is None:
            master = spark.sparkContext.master
            if not re.fullmatch(r"local(\[.*\])?", master):
                raise ValueError(f"set spark.checkpoint.dir to a folder that all executors of {master} share")
            own = tempfile.mkdtemp(prefix="plandistill-")
            atexit.register(shutil.rmtree, own, ignore_errors=True)
            spark.sparkContext.setCheckpointDir(f"file://{own}")
            found = f"file://{own}"
        configured = found
    elif spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(configured)
    return configured.rstrip("/")


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/llm-{label}-{uuid.uuid4().hex[:12]}"


def park(df: DataFrame, label: str) -> DataFrame:
    """Write a table into the shared folder and read it back: lineage ends here."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.parked_at = path
    return out


def drop(*parked: DataFrame) -> None:
    """Remove parked tables that no later plan reads."""
    for df in parked:
        drop_path(df.sparkSession, df.parked_at)


def drop_path(spark: SparkSession, path: str) -> None:
    """Remove a scratch table that no later plan reads."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def sliced(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The batches in slices of so many rows; Spark bounds the bytes of a batch, this what
    is made of one at a time. No session setting is touched."""
    for b in batches:
        for i in range(0, len(b), rows):
            yield b.slice(i, rows)


#: Bits of the filter in ``maybe_in``: at most 2 ** (BITS - 6) rows of two longs are broadcast.
FILTER_BITS = 24


def maybe_in(df: DataFrame, key: str, ids: DataFrame, flag: str) -> DataFrame:
    """``df`` with a boolean column: false proves that ``key`` isn't among the ids (one column).

    A Bloom filter with one hash and a fixed number of bits, so its broadcast is bounded
    (2 ** 18 rows); an exact join has to follow for the rows that it leaves open. What it
    spares shrinks as ids fill it, its results stay true at every size.
    """
    place = lambda c: F.pmod(F.xxhash64(F.col(c).cast("long")), F.lit(1 << FILTER_BITS))
    bits = ids.toDF("_id").where("_id is not null").select(place("_id").alias("h"))
    spots = bits.groupBy(F.shiftright("h", 6).alias("_spot")).agg(F.bit_or(F.expr("shiftleft(1L, cast(h & 63 as int))")).alias("_mask"))
    spots = spots.hint("broadcast")
    out = df.withColumn("_h", F.coalesce(place(key), F.lit(-1).cast("long"))).withColumn("_at", F.shiftright("_h", 6))
    out = out.join(spots, F.col("_at") == F.col("_spot"), "left")
    held = F.expr("(shiftright(_mask, cast(_h & 63 as int)) & 1L) = 1")
    return out.withColumn(flag, F.coalesce(held, F.lit(False))).drop("_h", "_at", "_spot", "_mask")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind ``value`` once for ``body``: a one-element transform keeps the optimiser from
    copying an expensive expression into every use."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words(text: Column) -> Column:
    """Array of words of a text; null and blank texts give an empty array."""
    bare = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACES))
    return F.when(F.length(bare) > 0, F.split(bare, GAP)).otherwise(F.array().cast("array<string>"))


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")
