"""Pools, success-gated stratified quotas, waves, and reports on the sets they make."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Training mix by complexity class: (train, in-domain validation, out-of-domain validation).
MIX = {"single": (295, 37, 46), "sub": (229, 39, 31), "joinset": (398, 57, 60), "joinset_sub": (78, 17, 13)}


def seeded(seed: int, key: Column | str) -> Column:
    return F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key) if isinstance(key, str) else key))


def split_pools(df: DataFrame, db: str = "db_id", ood: float = 0.25, seed: int = 42) -> DataFrame:
    """``df`` with pool: the last quarter of the distinct database ids in hash order is OOD.

    The global window runs over one row for each database. Rows without a database go to the
    in-domain pool: no out-of-domain claim can rest on them."""
    dbs = df.select(db).where(F.col(db).isNotNull()).distinct()
    ranked = dbs.select(db, F.row_number().over(Window.orderBy(seeded(seed, db), db)).alias("r"), F.count("*").over(Window.partitionBy(F.lit(1))).alias("n"))
    pools = ranked.select(db, F.when(F.col("r") > F.col("n") - F.round(F.col("n") * ood), "OOD").otherwise("ID").alias("pool"))
    return df.join(pools, db, "left").withColumn("pool", F.coalesce("pool", F.lit("ID")))


def component_pools(databases: dict[str, tuple[str, ...]], ood: float = 0.25, seed: int = 42) -> dict[str, str]:
    """Pools for named databases such that no table is shared: databases that share tables move
    together; single ones become OOD in hash order until the share is reached."""
    import hashlib

    group = {d: {d} for d in databases}
    for a in databases:
        for b in databases:
            if set(databases[a]) & set(databases[b]) and group[a] is not group[b]:
                both = group[a] | group[b]
                for d in both:
                    group[d] = both
    alone = sorted((d for d in databases if len(group[d]) == 1), key=lambda d: hashlib.md5(f"{seed}|{d}".encode()).hexdigest())
    out = set(alone[: round(len(databases) * ood)])
    return {d: "OOD" if d in out else "ID" for d in databases}


def admit(completions: DataFrame, outcomes: DataFrame, key: str = "sample_id") -> DataFrame:
    """Completions with success: the SQL ran and gave the gold result (level SUCC of its
    outcome row). Without an outcome a completion isn't admitted."""
    level = outcomes.select(key, F.col("level").alias("_level"))
    return completions.join(level, key, "left").withColumn("success", F.coalesce(F.col("_level") == "SUCC", F.lit(False))).drop("_level")


def pair_signals(plan: DataFrame, prose: DataFrame, paired: bool = True, key: str = "sample_id") -> tuple[DataFrame, DataFrame]:
    """The two distillation sets of the comparison, which differ in the form of the trace only.
    ``paired`` keeps samples that both have; else each keeps its own."""
    if not paired:
        return plan, prose
    both = plan.select(key).intersect(prose.select(key))
    return plan.join(both, key, "left_semi"), prose.join(both, key, "left_semi")


def gold_set(bank: DataFrame, pool: str = "ID") -> DataFrame:
    """All human pairs of the pool, without a gate: question and gold SQL, part train."""
    return bank.where(F.col("pool") == pool).withColumn("part", F.lit("train"))


def sample_quota(df: DataFrame, quotas: dict[tuple[str, str], int], key: str = "sample_id", seed: int = 42) -> DataFrame:
    """Per (pool, stratum) the successes that come first in hash order, up to the quota, with rank.

    Spark limits each partition to the quota before the shuffle (a window group limit), so
    what moves is quotas times partitions, not all successes."""
    q = F.create_map(*[x for (p, s), n in quotas.items() for x in (F.lit(f"{p}|{s}"), F.lit(n))])
    w = Window.partitionBy("pool", "stratum").orderBy(seeded(seed, key), key)
    most = max(quotas.values(), default=0)
    ranked = df.where("success").withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= most)
    return ranked.where(F.col("rank") <= F.coalesce(F.element_at(q, F.concat_ws("|", "pool", "stratum")), F.lit(0)))


def build_sets(df: DataFrame, mix: dict[str, tuple[int, int, int]] = MIX, key: str = "sample_id", seed: int = 42) -> DataFrame:
    """Rows with part: ID ranks 1..k train, the next id_val, OOD ranks ood_val."""
    quotas = {("ID", s): a + b for s, (a, b, _) in mix.items()} | {("OOD", s): c for s, (_, _, c) in mix.items()}
    train = F.create_map(*[x for s, (a, _, _) in mix.items() for x in (F.lit(s), F.lit(a))])
    got = sample_quota(df, quotas, key, seed)
    return got.withColumn("part", F.when(F.col("pool") == "OOD", "ood_val").when(F.col("rank") <= F.element_at(train, F.col("stratum")), "train").otherwise("id_val"))


def scale_quotas(total: int, column: int = 0, mix: dict[str, tuple[int, int, int]] = MIX) -> dict[str, int]:
    """The mix's proportions at another total, by largest remainders."""
    whole = sum(v[column] for v in mix.values())
    exact = {s: total * v[column] / whole for s, v in mix.items()}
    out = {s: math.floor(x) for s, x in exact.items()}
    for s in sorted(exact, key=lambda s: (out[s] - exact[s], s))[: total - sum(out.values())]:
        out[s] += 1
    return out


def generate_until(candidates: DataFrame, complete: Callable[[DataFrame], DataFrame], quotas: dict[tuple[str, str], int], key: str = "sample_id", seed: int = 42, wave: float = 1.3) -> DataFrame:
    """Asks the teacher in waves of the hash order until each quota is full or nothing is left.

    ``complete`` adds success to the rows it gets. Equals ``sample_quota`` on all completions."""
    spark = candidates.sparkSession
    w = Window.partitionBy("pool", "stratum").orderBy(seeded(seed, key), key)
    ranked = candidates.withColumn("order", F.row_number().over(w)).persist()
    sizes = {(r.pool, r.stratum): r.n for r in ranked.groupBy("pool", "stratum").agg(F.count("*").alias("n")).collect()}
    upto = dict.fromkeys(quotas, 0)
    got, full = None, dict.fromkeys(quotas, 0)
    while True:
        ask = {g: (upto[g], min(sizes.get(g, 0), upto[g] + max(1, math.ceil((quotas[g] - full[g]) * wave)))) for g in quotas if full[g] < quotas[g] and upto[g] < sizes.get(g, 0)}
        if not ask:
            break
        ranges = spark.createDataFrame([(*g, a, b) for g, (a, b) in ask.items()], "pool string, stratum string, lo int, hi int")
        rows = ranked.join(F.broadcast(ranges), ["pool", "stratum"]).where((F.col("order") > F.col("lo")) & (F.col("order") <= F.col("hi"))).drop("lo", "hi")
        done = complete(rows)
        both = (done if got is None else got.unionByName(done)).persist()
        both.count()
        if got is not None:
            got.unpersist()
        got = both
        for g, (_, b) in ask.items():
            upto[g] = b
        for r in got.where("success").groupBy("pool", "stratum").agg(F.count("*").alias("n")).collect():
            if (r.pool, r.stratum) in full:
                full[r.pool, r.stratum] = r.n
    ranked.unpersist()
    return sample_quota(got if got is not None else candidates.withColumn("success", F.lit(False)), quotas, key, seed)


def quota_report(df: DataFrame, quotas: dict[tuple[str, str], int], key: str = "sample_id", seed: int = 42) -> DataFrame:
    """stratum by pool: wanted, got, tried and success rate; what is short shows as got < wanted."""
    wanted = df.sparkSession.createDataFrame([(p, s, n) for (p, s), n in quotas.items()], "pool string, stratum string, wanted int")
    tried = df.groupBy("pool", "stratum").agg(F.count("*").alias("tried"), F.count_if("success").alias("successes"))
    joined = wanted.join(tried, ["pool", "stratum"], "left").na.fill(0)
    return joined.select("pool", "stratum", F.col("wanted").cast("long").alias("wanted"), F.least("wanted", "successes").cast("long").alias("got"), "tried", F.when(F.col("tried") > 0, F.col("successes") / F.col("tried")).alias("success_rate"))


def mix_report(sets: DataFrame) -> DataFrame:
    n = sets.groupBy("part", "stratum").agg(F.count("*").alias("n"))
    return n.select("part", "stratum", "n", (100.0 * F.col("n") / F.sum("n").over(Window.partitionBy("part"))).alias("pct"))


def leak_report(df: DataFrame, db: str = "db_id", text: str = "question", key: str = "sample_id") -> DataFrame:
    """check, n: databases in both pools, samples in both, and OOD samples whose text (small
    letters, runs of white space as one space) is an ID sample's. Null texts equal nothing."""
    said = F.lower(F.btrim(F.regexp_replace(text, r"[\x20\x09-\x0D]+", " ")))
    marked = df.select("pool", F.col(db).alias("db"), F.col(key).alias("key"), F.md5(said).alias("said"))

    def shared(column: str) -> DataFrame:
        pools = marked.where(F.col(column).isNotNull()).groupBy(column).agg(F.count_if(F.col("pool") == "ID").alias("id"), F.count_if(F.col("pool") == "OOD").alias("ood"))
        return pools.where("id > 0 and ood > 0")

    both = [shared(c).agg(F.count("*").alias("n")).select(F.lit(f"{name} in both pools").alias("check"), "n") for c, name in (("db", "database"), ("key", "sample"))]
    told = shared("said").agg(F.coalesce(F.sum("ood"), F.lit(0)).alias("n")).select(F.lit("OOD text in ID").alias("check"), "n")
    return both[0].union(both[1]).union(told)
