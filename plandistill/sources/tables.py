"""Reading tables, the virtual databases over them, and the question bank."""

from __future__ import annotations

import hashlib
import json
import re
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: Virtual databases: id -> tables.
DATABASES = {
    "geo_crm": ("region", "nation", "customer"),
    "order_desk": ("customer", "orders"),
    "fulfilment": ("orders", "lineitem"),
    "sourcing": ("part", "supplier", "lineitem"),
    "supplier_geo": ("region", "nation", "supplier"),
    "regional_sales": ("region", "nation", "customer", "orders"),
    "full_star": ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"),
    "chat_log": ("conversations",),
    "vector_store": ("embeddings",),
    "clickstream": ("events",),
    "corpus_quality": ("documents", "labels", "benchmark"),
    "web_archive": ("pages",),
}
BANK_SCHEMA = "sample_id string, db_id string, stratum string, difficulty string, question string, gold_sql string"


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def register(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> SparkSession:
    """Temporary views of the named tables in the session given."""
    for n in names:
        read_table(spark, sf_dir, n).createOrReplaceTempView(n)
    return spark


def run_text(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    """A SQL text over just the tables it names, in a session of its own."""
    own = spark.newSession()
    names = tuple(t for t in TABLES if re.search(rf"\b{t}\b", sql))
    register(own, sf_dir, names)
    return own.sql(sql)


def bank_rows() -> list[dict[str, str]]:
    return json.loads(Path(__file__).with_name("bank.json").read_text())


def load_bank(spark: SparkSession) -> DataFrame:
    rows = [tuple(r[c.split()[0]] for c in BANK_SCHEMA.split(", ")) for r in bank_rows()]
    return spark.createDataFrame(rows, BANK_SCHEMA)


#: Ways to begin a question; they change its words and not its meaning.
LEADS = ("", "Please answer: ", "For the report: ", "We want to know: ", "Quick question. ", "From the database: ", "Tell me. ", "One more: ")


def expand_bank(rows: list[dict[str, str]], values: dict[str, list[str]], n: int, seed: int = 42, unlike: set[str] = frozenset()) -> list[dict[str, str]]:
    """Up to ``n`` variants of bank rows, dealt over the rows in turn and in md5 order of the seed.

    Slots are names that a column holds and numbers of two digits or more, where question and
    SQL both have them; a variant puts other names, moved numbers and another beginning, the
    same in question and SQL. Questions in ``unlike`` are left out, so banks stay apart."""
    known = {v: domain for domain in values.values() for v in domain}
    order = lambda *key: hashlib.md5("|".join(map(str, (seed, *key))).encode()).hexdigest()

    def variants(r: dict[str, str]) -> list[dict[str, str]]:
        names = [v for v in re.findall(r"'([^']*)'", r["gold_sql"]) if v in known and re.search(rf"\b{re.escape(v)}\b", r["question"])][:1]
        numbers = [x for x in re.findall(r"\b\d{2,}\b", r["gold_sql"]) if re.search(rf"\b{x}\b", r["question"])][:1]
        out = []
        for name in known[names[0]] if names else [None]:
            for move in (0, 1, 2, 3, 5, 8, 13, 21) if numbers else (0,):
                sql, asked = r["gold_sql"], r["question"]
                if names:
                    sql, asked = sql.replace(f"'{names[0]}'", f"'{name}'"), re.sub(rf"\b{re.escape(names[0])}\b", name, asked)
                if numbers:
                    other = str(int(numbers[0]) + move)
                    sql, asked = (re.sub(rf"\b{numbers[0]}\b", other, x) for x in (sql, asked))
                out += [r | {"gold_sql": sql, "question": lead + asked} for lead in LEADS]
        out = [v for v in out if v["question"] not in unlike]
        return sorted(out, key=lambda v: order(r["sample_id"], v["question"]))

    dealt, made = [variants(r) for r in rows], []
    for k in range(max(map(len, dealt), default=0)):
        made += [v[k] | {"sample_id": f"{v[k]['sample_id']}_{k}"} for v in dealt if k < len(v)]
    return made[:n] if n else made


def domains(spark: SparkSession, sf_dir: str) -> dict[str, list[str]]:
    """All distinct values of the name columns, for slots: a handful each by their meaning, and
    the same on every run."""
    columns = {"customer": "c_mktsegment", "region": "r_name", "part": "p_type", "orders": "o_orderstatus", "events": "event_type"}
    return {c: sorted(r[0] for r in read_table(spark, sf_dir, t, [c]).where(F.col(c).isNotNull()).distinct().collect()) for t, c in columns.items()}


def sink_path(spark: SparkSession, label: str) -> str:
    """A new path in the folder all executors share; a local one only where none is configured and
    the master is local."""
    shared = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not shared:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        shared = f"file://{tempfile.gettempdir()}"
    return f"{shared.rstrip('/')}/{label}-{uuid.uuid4().hex[:12]}"


def write_json_bank(bank: DataFrame, path: str) -> DataFrame:
    """The bank as JSON lines, and what its schema reads back."""
    bank.write.json(path)
    return bank.sparkSession.read.schema(BANK_SCHEMA).json(path)


def write_by_run(outcomes: DataFrame, path: str, run: str = "run_id") -> DataFrame:
    """Outcomes in one folder for each run; a filter on the run then reads its folder alone.

    The run is read back as a string. Rows are not gathered by run first: a hot run is written
    by all tasks that hold it."""
    outcomes.write.partitionBy(run).parquet(path)
    back = outcomes.withColumn(run, F.col(run).cast("string")).schema
    return outcomes.sparkSession.read.schema(back).parquet(path)
