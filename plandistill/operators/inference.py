"""Prompts, completers, extraction, and the registry of runs."""

from __future__ import annotations

import hashlib
import pickle
import random
import re
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

MAX_INPUT, MAX_OUTPUT = 15_000, 1_500
SQL_MARK = "### SQL"
#: run: (trained on, prompt, base).
RUNS = {"TEACH": (None, "plan", "teacher"), "BASE": (None, "plan", "student"), "GOT": ("none", "plan", "student"), "GOT_D": ("none", "direct", "student"), "FRD": ("prose", "prose", "student"), "FRD_X": ("prose", "plan", "student"), "PGD": ("plan", "plan", "student"), "BASE_7": (None, "plan", "second"), "FRD_7": ("prose", "prose", "second"), "PGD_7": ("plan", "plan", "second"), "PGD_HID": ("plan", "plan", "student")}
_ASK = {
    "plan": "Write the numbered steps by which an engine would answer the question (scan, filter, join, aggregate, sort), then the SQL.",
    "prose": "Think it through step by step in your own words, then write the SQL.",
    "direct": "Answer with SQL.",
    "decompose": "Split the question into smaller questions, answer each with SQL in order, then compose the SQL.",
    "divide": "If the question has independent parts, solve each part on its own and merge the parts into the SQL.",
}


def count_tokens(text: Column) -> Column:
    """Words and single marks, as a token count that both engines can take."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[A-Za-z0-9_]+|[^A-Za-z0-9_\s]")).cast("long")


def schema_text(schema: dict[str, list[tuple[str, str]] | DataFrame], sample_rows: int = 0) -> str:
    """Tables with columns and types, read from a DataFrame's schema where one is given. By
    default no records leave the engine; ``sample_rows`` adds that many of each DataFrame."""
    out = []
    for t, cols in sorted(schema.items()):
        pairs = cols.dtypes if isinstance(cols, DataFrame) else cols
        out.append(f"{t}({', '.join(f'{c} {k}' for c, k in pairs)})")
        if sample_rows and isinstance(cols, DataFrame):
            out += [f"  {tuple(r)}" for r in cols.limit(sample_rows).collect()]
    return "\n".join(out)


def build_prompt(questions: DataFrame, style: str, schemas: dict[str, str], shots: list[str] = ()) -> DataFrame:
    """``questions`` with prompt; oldest shots go first when the prompt is too long (flag fitted)."""
    texts = questions.sparkSession.createDataFrame(sorted(schemas.items()), "db_id string, schema string")
    head, tail = F.lit(_ASK[style]), F.concat(F.lit("Schema:\n"), "schema", F.lit("\nQuestion: "), "question", F.lit("\n"))
    prompts = F.array(*[F.concat_ws("\n\n", head, *[F.lit(s) for s in shots[k:]], tail) for k in range(len(shots) + 1)])
    joined = questions.join(F.broadcast(texts), "db_id").withColumn("options", prompts)
    fits = F.filter("options", lambda p: count_tokens(p) <= MAX_INPUT)
    return joined.withColumn("prompt", F.coalesce(F.get(fits, F.lit(0)), F.element_at("options", -1))).withColumn("fitted", F.size(fits) == len(shots) + 1).drop("options", "schema")


def _dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def _best(scored: DataFrame, k: int, *by: str) -> DataFrame:
    return scored.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("score"), "shot"))).where(F.col("rank") <= k)


def select_shots(questions: DataFrame, bank: DataFrame, k: int = 3, method: str = "similar", tables: int = 12, bits: int = 8, seed: int = 5) -> DataFrame:
    """id, shot, rank: examples from the bank (id, vector) for each question.

    similar: the nearest by cosine; the whole bank is searched, dealt in blocks, and each
    question's best ``k`` of every block meet. lsh: the nearest among those that share the signs
    of ``bits`` random directions in one of ``tables`` draws, for banks too large to search
    whole; a question may get fewer. static: the ``k`` smallest ids, the same for all."""
    q = questions.select("id", "vector", _dot("vector", "vector").alias("vv"))
    b = bank.select(F.col("id").alias("shot"), F.col("vector").alias("bv"), _dot("vector", "vector").alias("bb"))
    if method == "static":
        first = b.select("shot").orderBy("shot").limit(k + 1)  # one more, for a question that is itself among them
        met = q.select("id").join(F.broadcast(first), F.col("id") != F.col("shot")).withColumn("score", F.lit(0.0))
        return _best(met, k, "id")
    if method == "similar":
        blocks = int(bank.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        keyed = q.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
        dealt = b.withColumn("block", F.pmod(F.xxhash64("shot"), F.lit(blocks)).cast("int"))
    elif method == "lsh":
        width = bank.select(F.size("vector")).head()
        rng = random.Random(seed)
        planes = [[[rng.gauss(0, 1) for _ in range(width[0] if width else 0)] for _ in range(bits)] for _ in range(tables)]

        def signs(v: str) -> Column:
            bit = lambda p, i: F.when(F.aggregate(F.zip_with(v, F.array(*map(F.lit, p)), lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x) > 0, 1 << i).otherwise(0)
            keys = [F.lit(t << bits) + sum((bit(p, i) for i, p in enumerate(draw)), F.lit(0)) for t, draw in enumerate(planes)]
            return F.explode(F.array(*keys))

        keyed, dealt = q.withColumn("block", signs("vector")), b.withColumn("block", signs("bv"))
    else:
        raise ValueError(f"unknown method {method}")
    met = keyed.join(dealt, "block").where(F.col("id") != F.col("shot"))
    scored = met.select("block", "id", "shot", (_dot("vector", "bv") / F.sqrt(F.col("vv") * F.col("bb"))).alias("score"))
    near = _best(scored, k, "block", "id").drop("block", "rank")
    return _best(near.distinct() if method == "lsh" else near, k, "id")


def extract_sql(raw: Column) -> Column:
    """SQL after the mark, else in the last fence, else the last statement; null if none is there."""
    after = F.regexp_extract(raw, rf"(?s)^.*{SQL_MARK}\s*(?:```sql|```)?\s*(.*?)(?:```|\s*)$", 1)
    fence = F.regexp_extract(raw, r"(?s)^.*```(?:sql)?\s*(.*?)```", 1)
    statement = F.regexp_extract(raw, r"(?is)((?:\b(?:select|sel[a-z]{0,2}ct|slect|seelct|selec)\b|\bwith\b\s+\w+\s+as\b).*)$", 1)
    pick = F.coalesce(*[F.nullif(F.btrim(c, F.lit(" \t\r\n")), F.lit("")) for c in (after, fence, statement)])
    return F.when(F.rlike(pick, F.lit(r"(?i)^\W*(select|with|sel\w*)\b")), pick)


def assemble(samples: DataFrame, signal: str) -> DataFrame:
    """``samples`` (trace columns plan, prose, and gold_sql) with completion and its token count."""
    body = {"plan": F.col("plan"), "prose": F.col("prose"), "none": F.lit(None).cast("string")}[signal]
    return samples.withColumn("completion", F.concat_ws(f"\n{SQL_MARK}\n", body, "gold_sql") if signal != "none" else F.concat(F.lit(f"{SQL_MARK}\n"), "gold_sql")).withColumn("n_completion", count_tokens(F.col("completion")))


def _columns(q: str) -> int:
    """Columns of the outermost select list: its commas outside brackets, and one."""
    depth, n, inside = 0, 1, False
    for w in re.findall(r"'(?:[^']|'')*'|\w+|[^\s\w]", q.lower()):
        depth += (w == "(") - (w == ")")
        if depth == 0 and w == "select":
            inside = True
        elif depth == 0 and inside and w == "from":
            break
        n += depth == 0 and inside and w == ","
    return n


CHANGE = "concat(c1, '!') as c1"


def _changed(q: str) -> str:
    """The same shape with other values in the first column."""
    names = [f"c{i}" for i in range(1, _columns(q) + 1)]
    return f"select {', '.join([CHANGE, *names[1:]])} from ({q}) t({', '.join(names)})"


CORRUPTIONS: dict[str, Callable[[str], str]] = {
    "success": lambda q: q,
    "no output": lambda q: "I cannot answer this",
    "no such column": lambda q: re.sub(r"(?i)^(with .*?\) )?select (distinct )?", lambda m: m.group() + "nope_col, ", q, count=1),
    "no such table": lambda q: re.sub(r"(?i)\bfrom (\w+)", r"from \1_nope", q, count=1),
    "keyword": lambda q: re.sub(r"(?i)\bselect\b", "selct", q, count=1),
    "clause order": lambda q: q + " limit 3 where 1 = 1",
    "other": lambda q: re.sub(r"(?i)\bselect\b", "select nosuchfn(1),", q, count=1),
    "column mismatch": lambda q: f"select t.*, 1 as extra from ({q}) t",
    "row mismatch": lambda q: f"select * from ({q}) t union all select * from ({q}) u",
    "row & column mismatch": lambda q: f"select t.*, 1 as extra from (select * from ({q}) a union all select * from ({q}) b) t",
    "value mismatch": _changed,
    "empty output": lambda q: f"select * from ({q}) t where 1 = 0",
}


class NoisyCompleter:
    """Gives back the gold query, or a corruption of known class, by seeded hash and a profile
    of shares; evidence about the measuring code only. ``tell`` gives the class put in as the
    finish reason."""

    def __init__(self, profile: dict[str, float], seed: int = 42, tell: bool = False):
        self.profile, self.seed, self.tell = profile, seed, tell

    def __call__(self, sample_id: str, gold_sql: str, trace: str = "") -> tuple[str, str]:
        x, at = int(hashlib.md5(f"{self.seed}|{sample_id}".encode()).hexdigest()[:8], 16) / 2**32, 0.0
        leaf = "success"
        for leaf, share in self.profile.items():
            at += share
            if x < at:
                break
        made = CORRUPTIONS[leaf](gold_sql)
        return (made if leaf == "no output" else f"{trace}\n{SQL_MARK}\n{made}"), leaf

    def answer(self, row: dict) -> tuple[str, str]:
        raw, made = self(row["sample_id"], row["gold_sql"], row.get("plan") or "")
        return raw, made if self.tell else "end"


class EndpointCompleter:
    """Asks a function of the prompt's text, such as a client of a served model. A call that
    raises is made again, so it has to be idempotent; after ``tries`` the task fails."""

    def __init__(self, ask: Callable[[str], str], tries: int = 3):
        self.ask, self.tries = ask, tries

    def answer(self, row: dict) -> tuple[str, str]:
        for k in range(self.tries):
            try:
                return self.ask(row["prompt"]), "end"
            except Exception:
                if k + 1 == self.tries:
                    raise
        raise ValueError("tries has to be positive")


class ReplayCompleter:
    """Outputs recorded before (sample_id, raw); a sample without one has an empty output."""

    def __init__(self, recorded: DataFrame):
        self.recorded = recorded


_CUT = re.compile(r"[A-Za-z0-9_]+|[^A-Za-z0-9_\s]")


def infer(questions: DataFrame, completer, max_in: int = MAX_INPUT, max_out: int = MAX_OUTPUT) -> DataFrame:
    """``questions`` (with prompt) with raw, finish_reason and n_tokens: one output each, no votes,
    no repair. Prompts over ``max_in`` tokens aren't asked; outputs end at ``max_out``.

    One pass over the rows without a shuffle; the completer is broadcast once. Null prompts are
    empty prompts."""
    if isinstance(completer, ReplayCompleter):
        out = replay(questions, completer.recorded).withColumn("finish_reason", F.when(F.col("raw") == "", "missing").otherwise("end"))
        return out.withColumn("n_tokens", count_tokens(F.col("raw")))
    shared = questions.sparkSession.sparkContext.broadcast(cloudpickle.dumps(completer))
    names = questions.columns
    schema = StructType([*questions.schema.fields, StructField("raw", StringType()), StructField("finish_reason", StringType()), StructField("n_tokens", LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ask = pickle.loads(shared.value).answer
        for b in batches:
            raw, reasons, sizes = [], [], []
            for row in b.to_pylist():
                text, why = ("", "prompt too long") if len(_CUT.findall(row["prompt"] or "")) > max_in else ask(row)
                marks = list(_CUT.finditer(text or ""))
                if len(marks) > max_out:
                    text, why, marks = text[: marks[max_out - 1].end()], "length", marks[:max_out]
                raw.append(text)
                reasons.append(why)
                sizes.append(len(marks))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(raw, pa.string()), pa.array(reasons, pa.string()), pa.array(sizes, pa.int64())], names=[*names, "raw", "finish_reason", "n_tokens"])

    return questions.mapInArrow(run, schema)


def replay(samples: DataFrame, recorded: DataFrame) -> DataFrame:
    """Completions recorded before, joined to their samples; a missing one is an empty output."""
    return samples.join(recorded.select("sample_id", "raw"), "sample_id", "left").withColumn("raw", F.coalesce("raw", F.lit("")))
