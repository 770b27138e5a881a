"""Quality rules for documents, and verdicts on their hosts (built-in functions only).

Every text is measured once. Two hard rules decide on a document alone. Soft
rules (symbols, repeated lines, word length, capitals) are counted by host; a
host's failure rate is shrunk towards the corpus by a beta prior whose mean and
strength are fitted to all hosts by moments. Documents of a host with a shrunken
rate of ``host_limit`` or more have to pass the soft rules too: a clean document
of a poor host stays, a poor document of a good host gets the benefit of doubt.

Defined results: null text is a text without words; null host is a host of its
own; an empty table gives no rows; equal rows are judged alike; other columns
pass untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, let, park, words

SYMBOLS = "#*$%&|<>"
CAPITALS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
WINDOW = 5


def repeated_words(ws: Column) -> Column:
    """Words inside windows of ``WINDOW`` words that the text holds twice or more."""

    def covered(sorted_windows: Column) -> Column:
        twin = lambda i, j: F.element_at(sorted_windows, j).getField("h") == F.element_at(sorted_windows, i).getField("h")
        n = F.size(sorted_windows)
        at = F.transform(sorted_windows, lambda x, i: F.when(((i > 0) & twin(i + 1, F.greatest(i, F.lit(1)))) | ((i + 1 < n) & twin(i + 1, F.least(i + 2, n))), x.getField("i")))
        return let(F.sort_array(F.filter(at, lambda x: x.isNotNull())), lambda p: F.aggregate(F.zip_with(p, F.slice(p, 2, F.greatest(F.size(p), F.lit(1))), lambda a, b: F.least(F.lit(WINDOW), F.coalesce(b - a, F.lit(WINDOW)))), F.lit(0), lambda a, b: a + b))

    def of(w: Column) -> Column:
        windows = F.transform(F.sequence(F.lit(1), F.size(w) - WINDOW + 1), lambda i: F.xxhash64(*[F.element_at(w, i + k) for k in range(WINDOW)]))
        return let(windows, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), 0).otherwise(let(F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), covered)))

    return F.when(F.size(ws) <= WINDOW, 0).otherwise(of(ws))


def measure(docs: DataFrame, host: str = "source", columns: list[str] | None = None) -> DataFrame:
    """row (a struct of the named columns, all by default, so that no name clashes), host,
    n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_upper."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.btrim(x, F.lit(SPACES))) > 0)
    counts = let(words(F.col("text")), lambda w: F.struct(F.size(w).cast("long").alias("n_words"), repeated_words(w).cast("long").alias("n_repeat_words")))
    many = F.when(F.contains(text, F.lit("\n")), let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x)))).otherwise(0)
    without = lambda chars: F.length(F.translate(text, chars, ""))
    out = docs.select(
        F.struct(*(columns or docs.columns)).alias("row"),
        F.col(host).alias("host"),
        counts.alias("counts"),
        without(SPACES).cast("long").alias("word_chars"),
        (F.length(text) - without(SYMBOLS)).cast("long").alias("n_symbols"),
        many.cast("long").alias("n_dup_lines"),
        (F.length(text) - without(CAPITALS)).cast("long").alias("n_upper"),
    )
    return out.select("row", "host", "counts.n_words", "word_chars", "n_symbols", "n_dup_lines", "counts.n_repeat_words", "n_upper")


BASE_FAILED = "n_words < 10 or 100 * n_repeat_words > 20 * n_words"
#: A document fails softly by symbols in the place of words, words far too long or short, or capitals only.
SOFT_FAILED = "5 * n_symbols > n_words * 2 or word_chars > 15 * n_words or word_chars < 2 * n_words or 2 * n_upper > word_chars"


def host_rates(measured: DataFrame) -> DataFrame:
    """Per host: documents, failures and the failure rate under the fitted beta prior.

    Mean m of all documents and variance v of host rates (weighted by documents)
    give the prior's strength k = m(1-m)/v - 1, held to [1, 10 000].
    """
    per = park(measured.groupBy("host").agg(F.count("*").alias("n"), F.count_if(F.expr(f"({BASE_FAILED}) or ({SOFT_FAILED})")).alias("bad")), "hosts")
    prior = per.agg((F.sum("bad") / F.sum("n")).alias("m"), (F.sum(F.col("bad") * F.col("bad") / F.col("n")) / F.sum("n")).alias("sq"))
    m, v = F.col("m"), F.col("sq") - F.col("m") * F.col("m")
    k = F.when(v > 0, F.greatest(F.lit(1.0), F.least(F.lit(10000.0), m * (1 - m) / v - 1))).otherwise(10000.0)
    return per.join(F.broadcast(prior.select("m", k.alias("k")))).select("host", "n", "bad", ((F.col("bad") + m * F.col("k")) / (F.col("n") + F.col("k"))).alias("host_rate"))


def judge(docs: DataFrame, host: str = "source", host_limit: float = 0.3, columns: list[str] | None = None) -> DataFrame:
    """What ``measure`` gives, with host_rate, base_failed and kept.

    The measured rows are written once: texts are not measured again for the hosts.
    """
    measured = park(measure(docs, host, columns), "measures")
    rates = host_rates(measured).select(F.col("host").alias("rated"), "host_rate")
    out = measured.join(rates, measured["host"].eqNullSafe(rates["rated"]), "left").drop("rated")
    out = out.withColumn("base_failed", F.expr(BASE_FAILED))
    return out.withColumn("kept", ~F.col("base_failed") & ~((F.col("host_rate") >= host_limit) & F.expr(SOFT_FAILED)))
