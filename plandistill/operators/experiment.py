"""The experiment end to end: distillation sets from a teacher, students by training signal, runs.

Every run answers the questions of its bank once, greedily; its SQL is executed beside the
gold SQL and classified. Sets come from the expanded bank: teacher outputs in waves, admitted
if they run and give the gold result, until each class's quota is full. Students train in
parallel, a run to a task: a distillation set is as large as its quotas, not as the data.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import complexity, ir
from ..sources.tables import DATABASES, bank_rows, domains, expand_bank, read_table, sink_path
from . import execution, inference, language, sampling
from .language import Decode, Example, Student

#: What the stand-in for the teacher does to gold queries; the measures' code sees the rest.
TEACHER = {"success": 0.8, "no such column": 0.04, "value mismatch": 0.06, "empty output": 0.04, "column mismatch": 0.04, "keyword": 0.02}
#: Base students: samples and passes that their base saw before it was frozen.
BASES = {"student": (96, 6), "second": (48, 3)}
SAMPLE = "sample_id string, db_id string, stratum string, difficulty string, question string, gold_sql string, pool string, plan string, prose string"


def schema_of(spark: SparkSession, sf_dir: str) -> dict[str, dict[str, list[str]]]:
    """Tables and columns of each database, read from the data."""
    columns = {t: read_table(spark, sf_dir, t).columns for t in sorted({t for ts in DATABASES.values() for t in ts})}
    return {d: {t: columns[t] for t in ts} for d, ts in DATABASES.items()}


def plan_traces(spark: SparkSession, sf_dir: str, asked: list[tuple[str, str]], threads: int = 8, source: str = "analyzed") -> dict[tuple[str, str], list[ir.Step]]:
    """Steps of each different (database, SQL), planned once in its database's session.

    Only Catalyst runs, on the driver: one plan for each different text, no job."""
    sessions = {db: execution.database_session(spark, sf_dir, db) for db in sorted({d for d, _ in asked})}
    todo = sorted(set(asked))
    with ThreadPoolExecutor(threads) as pool:
        return dict(zip(todo, pool.map(lambda x: ir.plan_ir(sessions[x[0]], x[1], source), todo), strict=True))


def brief(steps: list[ir.Step]) -> list[ir.Step]:
    """Steps with what they read in place of expressions: the form that the student learns."""
    return [ir.Step(s.number, s.op, s.inputs, s.args.split(" as ")[0] if s.op == "SCAN" else ", ".join(s.reads), s.emits[:6] if s.op in ("AGGREGATE", "PROJECT") else []) for s in steps]


def with_traces(spark: SparkSession, sf_dir: str, rows: list[dict[str, str]]) -> DataFrame:
    """Bank rows with pool, plan and prose trace."""
    pools = sampling.component_pools(DATABASES)
    steps = plan_traces(spark, sf_dir, [(r["db_id"], r["gold_sql"]) for r in rows])
    out = []
    for r in rows:
        s = brief(steps[r["db_id"], r["gold_sql"]])
        out.append((r["sample_id"], r["db_id"], r["stratum"], r["difficulty"], r["question"], r["gold_sql"], pools[r["db_id"]], ir.render_plan(s), ir.render_prose(s, r["sample_id"])))
    return spark.createDataFrame(out, SAMPLE)


def judge(spark: SparkSession, sf_dir: str, completions: DataFrame, seconds: float | None = 600.0) -> DataFrame:
    """``completions`` (raw, db_id, gold_sql, ...) with sql, level, leaf and ok. Each different
    query of a database (by its tokens, so spacing doesn't matter) runs once; only digests
    reach the driver."""
    made = completions.withColumn("sql", inference.extract_sql(F.col("raw")))
    pairs = [tuple(r) for r in made.select("db_id", "sql", "gold_sql").distinct().collect()]
    said = lambda d, q: (d, " ".join(language.split_tokens(q)))
    texts = {said(d, q): q for d, a, b in sorted(pairs, key=str, reverse=True) for q in (a, b) if q}
    ran = execution.run_many(spark, sf_dir, [(d, q) for (d, _), q in texts.items()], seconds=seconds)
    found = {k: ran[k[0], q] for k, q in texts.items()}
    judged = [(d, a, b, *execution.outcome(found[said(d, a)] if a else None, found[said(d, b)])) for d, a, b in pairs]
    verdicts = spark.createDataFrame(judged, "db string, s string, g string, level string, leaf string")
    on = (F.col("db_id") == F.col("db")) & F.col("sql").eqNullSafe(F.col("s")) & (F.col("gold_sql") == F.col("g"))
    return made.join(F.broadcast(verdicts), on).drop("db", "s", "g").withColumn("ok", F.col("level") == "SUCC")


def distillation_sets(spark: SparkSession, sf_dir: str, total: int = 1000, seed: int = 42, profile: dict[str, float] = TEACHER) -> tuple[DataFrame, DataFrame]:
    """(sets, bank): teacher outputs admitted up to the quotas of a mix with ``total`` training
    samples, with part, and the expanded bank that they come from."""
    mix = {s: tuple(sampling.scale_quotas(round(total * share), k)[s] for k, share in enumerate((1.0, 0.15, 0.15))) for s in sampling.MIX}
    rows = expand_bank(bank_rows(), domains(spark, sf_dir), 0, seed)
    bank = with_traces(spark, sf_dir, rows)
    quotas = {("ID", s): a + b for s, (a, b, _) in mix.items()} | {("OOD", s): c for s, (_, _, c) in mix.items()}
    teacher = inference.NoisyCompleter(profile, seed)

    def complete(wave: DataFrame) -> DataFrame:
        said = inference.infer(wave.withColumn("prompt", F.col("question")), teacher)
        return sampling.admit(said, judge(spark, sf_dir, said).select("sample_id", "level"))

    admitted = sampling.generate_until(bank, complete, quotas, seed=seed)
    path = sink_path(spark, "sets")
    sampling.build_sets(admitted.withColumn("success", F.lit(True)), mix, seed=seed).write.parquet(path)
    return spark.read.parquet(path), bank


def dev_bank(spark: SparkSession, sf_dir: str, seen: DataFrame, seed: int, n: int = 48) -> DataFrame:
    """Questions for evaluation: variants of all templates by another seed, none of them seen."""
    unlike = {r[0] for r in seen.select("question").distinct().collect()}  # as many as the quotas and bank
    return with_traces(spark, sf_dir, expand_bank(bank_rows(), domains(spark, sf_dir), n, seed, unlike))


def _signal(signal: str, r) -> str:
    trace = {"plan": r.plan, "prose": r.prose, "none": ""}[signal]
    return f"{trace}\n{inference.SQL_MARK}\n{r.gold_sql}"


def train_variants(sets: DataFrame, gold: DataFrame, schemas: dict, runs: dict[str, tuple] = inference.RUNS, epochs: int = 10, lr: float = 2e-3, r: int = 64, alpha: float = 128.0, width: int = 64) -> DataFrame:
    """key, model (bytes), curve: one student for each different (signal, style, base) of the
    runs, trained in parallel. Prose and plan students use the same sets; gold-only ones all
    human pairs with the direct prompt. A base sees a few gold pairs first and is then frozen."""
    jobs = sorted({(base, signal or "", trained_style(run, signal, style)) for run, (signal, style, base) in runs.items() if base in BASES})
    columns = ["sample_id", "db_id", "question", "gold_sql", "plan", "prose", "part"]
    data = sets.select(*columns).withColumn("source", F.lit("set")).unionByName(gold.select(*columns).withColumn("source", F.lit("gold")))
    plans = sets.sparkSession.createDataFrame(jobs, "base string, signal string, style string")
    work = data.crossJoin(F.broadcast(plans))  # a dozen jobs at most

    def run(key: tuple, f: pd.DataFrame) -> pd.DataFrame:
        base, signal, style = key
        f = f.sort_values(["source", "sample_id"])
        names = {d: language.slots(t) for d, t in schemas.items()}
        example = lambda x, s, kind: Example(kind, x.question, x.db_id, language.encode(_signal(s, x), x.question, names[x.db_id]))
        pool, human = f[f.source == "set"], f[f.source == "gold"]
        words = language.vocabulary([language.encode(_signal(s, x), x.question, names[x.db_id]) for x in f.itertuples() for s in ("plan", "prose")])
        student = Student(words, width, r, alpha)
        n, passes = BASES[base]
        student.fit([example(x, "none", "direct") for x in human.head(n).itertuples()], [], epochs=passes, lr=3e-3, full=True)
        student.quantise()
        curve: list[dict] = []
        if signal:
            chosen = human if signal == "none" else pool[pool.part == "train"]
            valid = [example(x, signal, style) for x in pool[pool.part != "train"].itertuples()]
            curve = student.fit([example(x, signal, style) for x in chosen.itertuples()], valid, size=15 if signal == "none" else 6, epochs=epochs, lr=lr)
        rows = [(c["step"], float(c["epoch"]), float(c["train"]), float(c["loss"])) for c in curve]
        return pd.DataFrame({"base": [base], "signal": [signal], "style": [style], "model": [pickle.dumps(student)], "trainable": [student.n_trainable()], "total": [student.n_total()], "curve": [[{"step": a, "epoch": b, "train": c, "loss": d} for a, b, c, d in rows]]})

    kind = "base string, signal string, style string, model binary, trainable long, total long, curve array<struct<step:int,epoch:double,train:double,loss:double>>"
    path = sink_path(sets.sparkSession, "students")
    work.groupBy("base", "signal", "style").applyInPandas(run, kind).write.parquet(path)
    return sets.sparkSession.read.parquet(path)


def completion_nll(samples: DataFrame, model: bytes, schemas: dict, signal: str, style: str) -> DataFrame:
    """sample_id, nll and n_tok of each sample's completion under a student: the prompt is read
    and isn't scored. One pass; the model is broadcast packed."""
    shared = samples.sparkSession.sparkContext.broadcast(model)
    names = {d: language.slots(t) for d, t in schemas.items()}

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        student = pickle.loads(shared.value)
        for f in frames:
            got = [student.nll([Example(style, x.question, x.db_id, language.encode(_signal(signal, x), x.question, names[x.db_id]))]) for x in f.itertuples()]
            yield pd.DataFrame({"sample_id": f["sample_id"], "nll": [g[0] for g in got], "n_tok": [g[1] for g in got]})

    return samples.select("sample_id", "db_id", "question", "gold_sql", "plan", "prose").mapInPandas(run, "sample_id string, nll double, n_tok long")


def rank_sweep(sets: DataFrame, gold: DataFrame, schemas: dict, ranks: tuple[int, ...] = (4, 16, 64)) -> DataFrame:
    """r, trainable and the least validation loss of the plan student at each adapter rank, at
    the same scale alpha / r."""
    out = None
    for r in ranks:
        one = train_variants(sets, gold, schemas, {"PGD": ("plan", "plan", "student")}, r=r, alpha=2.0 * r)
        least = F.array_min(F.transform("curve", lambda c: c["loss"]))
        one = one.select(F.lit(r).alias("r"), "trainable", F.round(least, 6).alias("loss"))
        out = one if out is None else out.union(one)
    return out


def trained_style(run: str, signal: str | None, style: str) -> str:
    """The prompt style of training: plan students by plan prompts, prose students by prose
    prompts, gold-only ones by direct prompts, whatever the run asks later."""
    return {"plan": "plan", "prose": "prose", "none": "direct"}.get(signal or "", "plan")


class StudentCompleter:
    """Answers with a trained student; the prompt style is the run's."""

    def __init__(self, model: bytes, style: str, schemas: dict, limits: Decode):
        self.model, self.style, self.limits = model, style, limits
        self.names = {d: language.slots(t) for d, t in schemas.items()}

    def answer(self, row: dict) -> tuple[str, str]:
        made, reason = self._open().greedy(Example(self.style, row["question"], row["db_id"]), self.limits)
        return language.decode(made, row["question"], self.names[row["db_id"]]), reason

    def _open(self) -> Student:
        if not hasattr(self, "student"):
            self.student = pickle.loads(self.model)
        return self.student

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "student"}


def run_variants(spark: SparkSession, sf_dir: str, total: int = 96, runs: dict[str, tuple] = inference.RUNS, limits: Decode = Decode(), seed: int = 42, n_dev: int = 48) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(outcomes, students, sets) of all runs. ``total`` scales the distillation sets."""
    schemas = schema_of(spark, sf_dir)
    sets, bank = distillation_sets(spark, sf_dir, total, seed)
    gold = sampling.gold_set(bank.join(sets.where("part <> 'train'").select("sample_id"), "sample_id", "left_anti"))
    gold = gold.where(sampling.seeded(seed, "sample_id") < "80") if total < 1000 else gold
    students = train_variants(sets, gold, schemas, runs)
    models = {(r.base, r.signal, r.style): bytes(r.model) for r in students.collect()}  # a dozen at most
    seen = sets.select("question").union(gold.select("question"))
    dev, hidden = dev_bank(spark, sf_dir, seen, seed + 2, n_dev), dev_bank(spark, sf_dir, seen, seed + 1, n_dev)
    said = None
    for run, (signal, style, base) in runs.items():
        questions = (hidden if run.endswith("_HID") else dev).withColumn("prompt", F.col("question"))
        if base == "teacher":
            answer = inference.NoisyCompleter({"success": 0.55, "value mismatch": 0.15, "empty output": 0.05, "row mismatch": 0.1, "no such column": 0.1, "keyword": 0.05}, seed)
        else:
            answer = StudentCompleter(models[base, signal or "", trained_style(run, signal, style)], style, schemas, limits)
        one = inference.infer(questions, answer).withColumn("run", F.lit(run))
        said = one if said is None else said.unionByName(one)
    path = sink_path(spark, "completions")
    said.write.parquet(path)
    outcomes = judge(spark, sf_dir, spark.read.parquet(path)).withColumn("constructs", complexity.constructs(F.col("gold_sql")))
    path = sink_path(spark, "outcomes")
    outcomes.write.parquet(path)
    return spark.read.parquet(path), students, sets


_done: dict[tuple[str, str], tuple[DataFrame, DataFrame, DataFrame]] = {}


def results(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``run_variants`` once for each application and data folder; the queries that report on it share it."""
    key = spark.sparkContext.applicationId, sf_dir
    if key not in _done:
        _done.clear()
        _done[key] = run_variants(spark, sf_dir)
    return _done[key]
