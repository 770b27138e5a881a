"""Registered queries: the bank, relational operators, and the experiment workloads as tapes.

A tape reads a given table as experiment rows (outcomes, curves, samples), so the measure's
function runs at the table's scale and has SQL to compare with.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import execution, experiment, inference, metrics, relational, sampling, student
from .plans import complexity, ir
from .sources.tables import DATABASES, TABLES, bank_rows, load_bank, read_table, run_text, sink_path, write_by_run, write_json_bank
from .streaming import monitor

Query = Callable[[SparkSession, str], DataFrame]

#: Relational operators around the methods; the same text runs in both engines.
SQL = {
    "scan_prune": "select l_orderkey, l_quantity from lineitem",
    "filter_conj": "select p_partkey from part where p_size > 20 and p_retailprice < 1500 and p_brand <> 'Brand#11'",
    "filter_in": "select o_orderkey from orders where o_orderpriority in ('1-URGENT', '2-HIGH')",
    "filter_between": "select o_orderkey, o_totalprice from orders where o_totalprice between 100000 and 120000",
    "filter_like": "select page_id from pages where url like 'https://%' and url not like '%page=%'",
    "filter_null": "select n_name from nation left join supplier on s_nationkey = n_nationkey and s_acctbal > 9000 where s_suppkey is null",
    "project_case": "select p_partkey, case when p_size < 15 then 'small' when p_size < 35 then 'medium' else 'large' end as band from part",
    "join_inner_hash": "select /*+ shuffle_hash(customer) */ o_orderkey, c_name from orders join customer on o_custkey = c_custkey",
    "join_broadcast": "select /*+ broadcast(nation) */ c_custkey, n_name from customer join nation on c_nationkey = n_nationkey",
    "join_sort_merge": "select /*+ merge(orders, lineitem) */ o_orderstatus, count(*) as n from orders join lineitem on l_orderkey = o_orderkey group by o_orderstatus",
    "join_left": "select n_name, count(s_suppkey) as n from nation left join supplier on s_nationkey = n_nationkey and s_acctbal > 5000 group by n_name",
    "join_right": "select n_name, count(s_suppkey) as n from supplier right join nation on s_nationkey = n_nationkey group by n_name",
    "join_full": "select coalesce(a.k, b.k) as k, a.n as suppliers, b.n as customers from (select s_nationkey as k, count(*) as n from supplier where s_acctbal > 5000 group by s_nationkey) a full join (select c_nationkey as k, count(*) as n from customer where c_acctbal > 9000 group by c_nationkey) b on a.k = b.k",
    "join_semi": "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 400000)",
    "join_anti": "select doc_id from documents where not exists (select 1 from labels where labels.doc_id = documents.doc_id)",
    "join_cross": "select r_name, s.seg from region cross join (select distinct c_mktsegment as seg from customer) s",
    "join_theta": "select a.p_partkey as x, b.p_partkey as y from part a join part b on a.p_brand = b.p_brand and a.p_partkey < b.p_partkey and abs(a.p_retailprice - b.p_retailprice) < 1",
    "join_range": "select lo, count(*) as n from orders join (values (0, 100000), (100000, 250000), (250000, 600000)) as bands(lo, hi) on o_totalprice >= lo and o_totalprice < hi group by lo",
    "join_interval": "select count(*) as n from events p join events k on p.user_id = k.user_id and k.ts < p.ts and k.ts >= p.ts - interval '1' hour where p.event_type = 'purchase' and k.event_type = 'click'",
    "join_self": "select a.conv_id, a.turn from conversations a join conversations b on a.conv_id = b.conv_id and b.turn = a.turn + 1 where a.role = 'user' and b.role = 'assistant'",
    "join_multiway": "select r_name, count(*) as n from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name",
    "agg_hash": "select l_returnflag, cast(sum(cast(l_quantity as decimal(18,2))) as decimal(18,2)) as qty, count(*) as n from lineitem group by l_returnflag",
    "agg_sort": "select l_linestatus, max(l_returnflag) as top from lineitem group by l_linestatus",
    "agg_distinct": "select p_type, count(distinct p_brand) as brands from part group by p_type",
    "agg_filter": "select l_linestatus, count(*) filter (where l_discount > 0.05) as n from lineitem group by l_linestatus",
    "agg_having": "select c_nationkey, count(*) as n from customer group by c_nationkey having count(*) > 3",
    "agg_rollup": "select r_name, c_mktsegment, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup(r_name, c_mktsegment)",
    "agg_cube": "select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube(o_orderstatus, o_orderpriority)",
    "agg_grouping_sets": "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())",
    "agg_maxby": "select user_id, max_by(event_id, value) as largest from events group by user_id",
    "win_rank": "select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt from orders window w as (partition by o_custkey order by o_totalprice desc, o_orderkey)",
    "win_lag_lead": "select event_id, lag(event_id) over w as prev, lead(event_id) over w as nxt from events window w as (partition by user_id order by ts, event_id)",
    "win_first_last": "select event_id, first_value(event_type) over (partition by user_id order by ts, event_id) as first_type from events",
    "win_rows_frame": "select event_id, max(value) over (partition by user_id order by ts, event_id rows between 6 preceding and current row) as top from events",
    "win_running_share": "select o_orderkey, cast(sum(cast(o_totalprice as decimal(18,2))) over (partition by o_custkey order by o_orderdate, o_orderkey) as decimal(24,2)) as upto from orders",
    "sort_limit": "select p_partkey, p_retailprice from part order by p_retailprice desc, p_partkey limit 10",
    "offset_page": "select p_partkey from part order by p_partkey limit 10 offset 10",
    "topk_group": "select c_mktsegment, c_custkey from (select c_mktsegment, c_custkey, row_number() over (partition by c_mktsegment order by c_acctbal desc, c_custkey) as rk from customer) t where rk <= 3",
    "set_union": "select c_nationkey as k from customer union select s_nationkey from supplier",
    "set_union_all": "select c_nationkey as k from customer union all select s_nationkey from supplier",
    "set_intersect": "select c_nationkey as k from customer intersect select s_nationkey from supplier",
    "set_intersect_all": "select c_nationkey as k from customer intersect all select s_nationkey from supplier",
    "set_except": "select doc_id from documents except select doc_id from labels",
    "set_except_all": "select c_nationkey as k from customer except all select s_nationkey from supplier",
    "sub_scalar": "select o_orderkey from orders where o_totalprice > (select 1.5 * avg(o_totalprice) from orders)",
    "sub_in": "select c_custkey from customer where c_nationkey in (select n_nationkey from nation where n_regionkey = 1)",
    "sub_not_in": "select p_partkey from part where p_partkey not in (select l_partkey from lineitem where l_quantity >= 49)",
    "sub_correlated": "select s_suppkey from supplier s where s_acctbal > (select avg(t.s_acctbal) from supplier t where t.s_nationkey = s.s_nationkey)",
    "sub_derived": "select max(n) as top from (select l_orderkey, count(*) as n from lineitem group by l_orderkey) t",
    "sub_cte": "with per as (select o_custkey, count(*) as n from orders group by o_custkey) select n, count(*) as customers from per group by n",
    "fn_string": "select doc_id, substring(text, 1, 20) as head, length(text) as n, upper(lang) as u, replace(lang, 'e', 'E') as l from documents",
    "fn_date": "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m from orders where o_orderdate + interval '30' day > timestamp '1998-01-01 00:00:00'",
    "fn_math": "select p_partkey, abs(p_size - 25) as d, greatest(p_size, 25) as g, floor(sqrt(p_size)) * 1.0 as f from part where p_size is not null",
    "fn_cond_null": "select n_name, coalesce(nullif(n_regionkey, 0), -1) as k from nation",
    "fn_hash": "select doc_id, md5(concat('42|', cast(doc_id as varchar(20)))) as h from documents",
    "agg_percentile": "select p_brand, round(percentile_cont(0.5) within group (order by p_retailprice), 6) as middle, round(percentile_cont(0.9) within group (order by p_retailprice), 6) as high from part group by p_brand",
    "win_share": "select o_orderkey, round(percent_rank() over w, 9) as pr, round(cume_dist() over w, 9) as cd from orders window w as (partition by o_custkey order by o_totalprice, o_orderkey)",
    "win_range_frame": "select event_id, count(*) over (partition by user_id order by ts range between interval '1' hour preceding and current row) as recent from events",
    "sub_exists": "select s_suppkey from supplier where exists (select 1 from lineitem where l_suppkey = s_suppkey and l_quantity > 49)",
    "sub_not_exists": "select s_suppkey from supplier where not exists (select 1 from lineitem where l_suppkey = s_suppkey and l_discount > 0.09 and l_quantity > 48)",
    "sub_nested": "select n_name from nation where n_nationkey in (select c_nationkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > (select 1.9 * avg(o_totalprice) from orders)))",
    "w2_difficulty": "select case when o_totalprice < 150000 then 'simple' when o_totalprice < 400000 then 'moderate' else 'challenging' end as difficulty, o_orderstatus as run, count(*) as n from orders group by 1, 2",
}

_DIFF = "case when o_totalprice < 150000 then 'simple' when o_totalprice < 400000 then 'moderate' else 'challenging' end"
_LEVEL = "case o_orderpriority when '1-URGENT' then 'SUCC' when '3-MEDIUM' then 'SYN' when '4-NOT SPECIFIED' then 'GEN' else 'SEM' end"


def _asked(spark: SparkSession, sf_dir: str, texts: list[tuple[str, str, str]], limits: bool = True) -> DataFrame:
    """Queries (c_custkey, sample_id, db_id, sql) as customers ask them: customer k the one at place
    k mod n of ``texts`` (sample, database, SQL), with the segment in a comment. Who is in debt
    sets a limit where the query has none."""
    # dealt anew, as the few tasks that read a small file would do all the work on its texts
    c = read_table(spark, sf_dir, "customer", ["c_custkey", "c_acctbal", "c_mktsegment"]).repartition("c_custkey")
    known = spark.createDataFrame([(k, *r) for k, r in enumerate(texts)], "k long, sample_id string, db_id string, text string")
    said = F.coalesce(F.regexp_replace("c_mktsegment", r"[\r\n]", " "), F.lit(""))
    limit = F.when(F.lit(limits) & (F.col("c_acctbal") < 0) & ~F.rlike("text", F.lit(r"limit \d+$")), F.concat(F.lit("\nlimit "), F.length(said))).otherwise("")
    asked = c.join(F.broadcast(known), F.pmod("c_custkey", F.lit(len(texts))) == F.col("k"))
    return asked.select("c_custkey", "sample_id", "db_id", F.concat("text", limit, F.lit("\n-- "), said).alias("sql"))


def _by_text(asked: DataFrame, tell: Callable[[list[tuple[str, str]]], list[tuple]], schema: str) -> DataFrame:
    """``asked`` with what the driver tells of each different (db_id, sql): Catalyst isn't in tasks.

    The texts that reach the driver are as many as queries times segments, not as customers."""
    texts = [tuple(r) for r in asked.select("db_id", "sql").distinct().collect()]
    told = asked.sparkSession.createDataFrame([(*x, *y) for x, y in zip(texts, tell(texts), strict=True)], f"db_id string, sql string, {schema}")
    return asked.join(F.broadcast(told), ["db_id", "sql"])


def _bank_texts() -> list[tuple[str, str, str]]:
    return [(r["sample_id"], r["db_id"], r["gold_sql"]) for r in bank_rows()]


def _orders(spark: SparkSession, sf_dir: str, *cols: str) -> DataFrame:
    return read_table(spark, sf_dir, "orders", list(cols))


def w1_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "source", "lang", "n_chars"]).join(read_table(spark, sf_dir, "labels", ["doc_id", "quality"]), "doc_id")
    linked, nested = F.col("lang") != "en", F.col("n_chars") > 1475
    stratum = F.when(linked & nested, "joinset_sub").when(linked, "joinset").when(nested, "sub").otherwise("single")
    return sampling.split_pools(docs.withColumn("stratum", stratum).withColumn("success", F.col("quality") == 1), "source")


#: Quotas of the samples tape; one is out of reach on purpose.
W1_QUOTAS = {("ID", s): n for s, n in (("single", 20), ("sub", 25), ("joinset", 15), ("joinset_sub", 10))} | {("OOD", s): n for s, n in (("single", 5), ("sub", 5), ("joinset", 5), ("joinset_sub", 100_000))}


def w1_quota(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.sample_quota(w1_samples(spark, sf_dir), W1_QUOTAS, "doc_id").select("doc_id", "pool", "stratum", "rank")


def w1_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.quota_report(w1_samples(spark, sf_dir), W1_QUOTAS, "doc_id")


def w1_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "source", "text"])
    return sampling.leak_report(sampling.split_pools(docs, "source"), "source", "text", "doc_id")


def src_json_bank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bank as customers ask it, written as JSON lines and read back by its schema."""
    about = load_bank(spark).select("sample_id", "stratum", "difficulty", "question")
    asked = _asked(spark, sf_dir, _bank_texts()).join(F.broadcast(about), "sample_id")
    bank = asked.select(F.concat("sample_id", F.lit("|"), "c_custkey").alias("sample_id"), "db_id", "stratum", "difficulty", "question", F.col("sql").alias("gold_sql"))
    return write_json_bank(bank, sink_path(spark, "bank")).select("sample_id", "db_id", "stratum", "difficulty", "question", F.md5("gold_sql").alias("digest"))


def sink_partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _orders(spark, sf_dir, "o_orderkey", "o_orderpriority", "o_orderstatus")
    outcomes = o.select("o_orderkey", F.col("o_orderstatus").alias("run_id"), F.expr(_LEVEL).alias("level"))
    back = write_by_run(outcomes, sink_path(spark, "outcomes"))
    return back.where("run_id = 'F'").groupBy("level").agg(F.count("*").alias("n"))


def w2_ex(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _orders(spark, sf_dir, "o_totalprice", "o_orderstatus")
    return metrics.ex(o.withColumn("difficulty", F.expr(_DIFF)).withColumn("ok", F.col("o_orderstatus") == "F"), ["difficulty"])


def w3_sunburst(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = read_table(spark, sf_dir, "lineitem", ["l_linenumber", "l_returnflag", "l_linestatus"])
    level = F.when(F.col("l_returnflag") == "N", "SUCC").when(F.col("l_returnflag") == "R", "SEM").otherwise("SYN")
    return metrics.sunburst(li.select(F.col("l_linenumber").alias("run"), level.alias("level"), F.col("l_linestatus").alias("leaf")))


def w4_construct(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = read_table(spark, sf_dir, "documents", ["text", "n_chars", "lang"])
    parts = [F.when(F.contains("text", F.lit("\n")), "newline"), F.when(F.rlike("text", F.lit("[0-9]")), "digit"), F.when(F.contains("text", F.lit("@")), "at"), F.when(F.col("n_chars") > 1475, "long")]
    return metrics.ex_by_construct(d.select(F.array_compact(F.array(*parts)).alias("constructs"), (F.col("lang") == "en").alias("ok"), F.lit("en").alias("run")))


def w5_gains(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _orders(spark, sf_dir, "o_orderstatus", "o_orderpriority")
    return metrics.gains_losses(o.select((F.col("o_orderstatus") == "F").alias("teacher_ok"), F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").alias("student_ok")))


def w6_transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _orders(spark, sf_dir, "o_orderpriority", "o_custkey")
    return metrics.transitions(o.select(F.expr(_LEVEL).alias("src"), F.element_at(F.array(*map(F.lit, metrics.LEVELS)), (F.col("o_custkey") % 4 + 1).cast("int")).alias("dst")))


def w9_early_stop(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["user_id", "ts", "event_id", "value"])
    step = F.row_number().over(metrics.Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return metrics.early_stop(e.select(F.col("user_id").alias("run"), step.alias("step"), F.col("value").alias("loss")))


def w11_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read_table(spark, sf_dir, "conversations", ["role", "text"])
    return metrics.token_stats(c.select("role", inference.count_tokens(F.col("text")).alias("n_tokens")), "role")


def w12_nll(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read_table(spark, sf_dir, "conversations", ["conv_id", "turn", "role", "text"])
    pairs = student.bigrams(c.where("role = 'assistant'"), ["conv_id", "turn"])
    return student.count_nll(pairs, pairs.where("conv_id % 5 <> 0"), ["conv_id"])


def w14_shots(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]).select(F.col("vec_id").alias("id"), F.col("embedding").alias("vector"))
    return inference.select_shots(e.where("id % 50 = 0"), e, 3).select("id", "rank", "shot")


def join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last view at or before each purchase of the same user."""
    e = read_table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type"])
    seen = e.where("event_type = 'view'").select("user_id", "ts", F.col("ts").alias("seen"))
    return relational.asof_join(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), seen, "user_id", "ts", "seen", "last_view").select("event_id", F.date_format("last_view", "yyyy-MM-dd HH:mm:ss").alias("last_view"))


def join_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts of a brand whose prices differ by less than 1, each pair once."""
    return relational.near_pairs(read_table(spark, sf_dir, "part", ["p_partkey", "p_brand", "p_retailprice"]), "p_brand", "p_partkey", "p_retailprice", 1.0)


def agg_maxby(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's event of the largest value: the first id of several, as a scan in order of ids finds it."""
    e = read_table(spark, sf_dir, "events", ["user_id", "event_id", "value"])
    return e.groupBy("user_id").agg(relational.first_max_by(F.col("event_id"), F.col("value")).alias("largest"))


def agg_approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["event_type", "user_id"])
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


def agg_collect(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = read_table(spark, sf_dir, "nation", ["n_regionkey", "n_name"])
    return n.groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("nations"))


def pivot_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _orders(spark, sf_dir, "o_orderstatus", "o_orderpriority").withColumn("level", F.expr(_LEVEL))
    return o.groupBy("o_orderstatus").pivot("level", list(metrics.LEVELS)).count().na.fill(0)


def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    doubles = F.transform("embedding", lambda x: x.cast("double"))
    dot = F.aggregate(F.zip_with(doubles, F.reverse(doubles), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", F.round(relational.norm(F.col("embedding")), 6).alias("norm"), F.round(dot, 6).alias("dot"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read_table(spark, sf_dir, "conversations", ["conv_id", "role"]).groupBy("conv_id", "role").agg(F.count("*").alias("n"))
    m = c.groupBy("conv_id").agg(F.map_from_entries(F.collect_list(F.struct("role", "n"))).alias("m"))
    doubled = F.transform_values("m", lambda k, v: v * 2)
    return m.select("conv_id", F.array_join(F.array_sort(F.map_keys("m")), ",").alias("roles"), F.coalesce(F.try_element_at(doubled, F.lit("user")), F.lit(0)).alias("users_twice"))


def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["event_id", "props"])
    parsed = F.from_json("props", "k long")
    return e.select("event_id", parsed["k"].alias("k"), F.get_json_object("props", "$.k").cast("long").alias("again"), F.to_json(F.struct((parsed["k"] + 1).alias("k"))).alias("more"))


def udf_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "conversations", ["conv_id", "turn", "text"]).select("conv_id", "turn", relational.mark_count("text").alias("marks"))


def udf_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _asked(spark, sf_dir, _all_texts()).select("c_custkey", "sample_id", relational.keyword_count("sql").alias("n"))


def _curves(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["user_id", "ts", "event_id", "value"])
    step = F.row_number().over(metrics.Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return e.select(F.col("user_id").alias("run"), step.alias("step"), F.col("value").alias("loss"))


def udaf_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _curves(spark, sf_dir).where("step <= 1").groupBy("run").agg(relational.mean_gap("loss").alias("gap"))


def map_in_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.longest_word(read_table(spark, sf_dir, "conversations", ["conv_id", "text"]).withColumnRenamed("conv_id", "doc_id"))


def apply_in_pandas(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.early_stop_by_loop(_curves(spark, sf_dir))


def _tape(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Outcome rows over orders: run by status, level and leaf by priority, difficulty by price."""
    o = _orders(spark, sf_dir, "o_orderkey", "o_orderstatus", "o_orderpriority", "o_totalprice", "o_custkey")
    level = F.expr(_LEVEL)
    leaf = F.when(level == "SYN", F.when(F.col("o_custkey") % 2 == 0, "no such column").otherwise("keyword")).when(level == "SEM", "row mismatch").otherwise(level)
    return o.select(F.col("o_orderkey").alias("sample_id"), F.col("o_orderstatus").alias("run"), level.alias("level"), leaf.alias("leaf"), (level == "SUCC").alias("ok"), (F.col("o_custkey") % 97).alias("n_tokens"))


def e8_compare(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = metrics.compare_runs(_tape(spark, sf_dir), "F", "O")
    return got.select(*[F.round(c, 6).alias(c) for c in got.columns])


def e13_error_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.error_delta(_tape(spark, sf_dir), "F", "O").select("level", "leaf", "pct_a", "pct_b", F.round("delta", 6).alias("delta"))


def e16_train_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = _curves(spark, sf_dir).withColumn("seconds", F.col("step") * 30).withColumn("epoch", F.ceil(F.col("step") / 10))
    return metrics.train_cost(c).select("run", "minutes", "epochs", "steps", "best_step")


def e17_trilemma(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = spark.createDataFrame([("F", 100, 1000, False), ("O", 50, 1000, False)], "run string, trainable long, total long, leaves boolean")
    return metrics.trilemma(_tape(spark, sf_dir), sizes)


def e18_mcnemar(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _orders(spark, sf_dir, "o_orderstatus", "o_orderpriority")
    got = metrics.mcnemar(o.select((F.col("o_orderstatus") == "F").alias("teacher_ok"), F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").alias("student_ok")))
    return got.select("gains", "losses", F.round("chi2", 6).alias("chi2"))


def e18_bootstrap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.bootstrap_ci(_tape(spark, sf_dir), draws=100)


def e19_hallucination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.hallucination(_tape(spark, sf_dir))


def e20_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = metrics.between_bounds(_tape(spark, sf_dir), "F", "O")
    return got.select("run", "ex", F.round("position", 6).alias("position"))


def w1_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three sets on the samples tape, with their mix."""
    mix = {"single": (20, 5, 5), "sub": (25, 5, 5), "joinset": (15, 5, 5), "joinset_sub": (10, 5, 5)}
    sets = sampling.build_sets(w1_samples(spark, sf_dir), mix, "doc_id")
    got = sampling.mix_report(sets)
    return got.select("part", "stratum", "n", F.round("pct", 6).alias("pct"))


def t6_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return student.batches(read_table(spark, sf_dir, "documents", ["doc_id"]), 6, 0, "doc_id").select("doc_id", "batch")


#: Queries beside the bank whose structure is easily misread.
ODD_SQL = {
    "comma": "select c_name from customer, nation where c_nationkey = n_nationkey",
    "comma_alias": "select c.c_name, n.n_name from customer as c, nation n, region",
    "window": "select c_custkey, row_number() over (order by c_acctbal) as r from customer",
    "window_order": "select c_custkey, rank() over (partition by c_nationkey order by c_acctbal desc) as r from customer order by r",
    "quoted": "select 'a join b, union (select 1)' as x from region -- join nation",
    "derived": "select t.n from (select count(*) as n from orders) t, region",
    "in_list": "select c_custkey from customer where c_nationkey in (1, 2, 3) order by c_custkey limit 3",
    "functions": "select coalesce(c_name, 'x'), greatest(1, 2, 3) from customer",
    "extract": "select extract(year from o_orderdate), o_orderkey from orders",
    "distinct_from": "select o_orderkey from orders where o_orderstatus is distinct from 'F'",
    "cte": "with a as (select 1 as x), b as (select 2 as x) select * from a",
    "case": "select case when c_acctbal > 0 then 'a, b' else 'c' end as k, sum(c_acctbal) from customer group by 1 having count(*) > 1",
    "set": "select distinct n_name from nation except select r_name from region",
}


def _all_texts() -> list[tuple[str, str, str]]:
    return _bank_texts() + [(k, "full_star", q) for k, q in ODD_SQL.items()]


def s1_structure(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class and five constructs by the lexer, of the bank and of odd queries as customers ask them."""
    c = complexity.constructs(F.col("sql"))
    has = lambda k: F.array_contains("c", k).alias(k)
    return _asked(spark, sf_dir, _all_texts()).withColumn("c", c).select("c_custkey", "sample_id", complexity.complexity(F.col("sql")).alias("stratum"), has("join"), has("set_op"), has("order_by"), has("limit"), has("distinct"))


def m1_plan_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many steps of each kind the parsed plan of each query that a customer asks has, from its
    trace read back."""

    def traces(texts: list[tuple[str, str]]) -> list[tuple]:
        steps = experiment.plan_traces(spark, sf_dir, texts, source="parsed")
        return [(ir.render_plan(steps[x]),) for x in texts]

    asked = _by_text(_asked(spark, sf_dir, _bank_texts()), traces, "trace string")
    return asked.select("c_custkey", "sample_id", *_kinds())


def _kinds() -> list[Column]:
    """Steps of each kind in a column trace."""
    ops = F.regexp_extract_all("trace", F.lit(r"(?m)^STEP \d+ ([A-Z]+)"), F.lit(1))
    n = lambda op: F.size(F.filter(ops, lambda x: x == op)).cast("long")
    return [n("SCAN").alias("scans"), n("JOIN").alias("joins"), n("SETOP").alias("setops"), n("SORT").alias("sorts"), n("LIMIT").alias("limits")]


def _step_counts(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    bank = bank_rows()
    steps = experiment.plan_traces(spark, sf_dir, [(r["db_id"], r["gold_sql"]) for r in bank], source=source)
    texts = spark.createDataFrame([(r["sample_id"], ir.render_plan(steps[r["db_id"], r["gold_sql"]])) for r in bank], "sample_id string, trace string")
    return texts.select("sample_id", *_kinds())


def m6_plan_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps of each bank query by the plan that its trace is read from."""
    out = None
    for source in ("parsed", "analyzed", "optimized", "physical"):
        one = _step_counts(spark, sf_dir, source).withColumn("source", F.lit(source))
        out = one if out is None else out.unionByName(one)
    return out


def m3_lint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What lint and agreement say of the own trace of each query that a customer asks: nothing is wrong."""
    schemas = experiment.schema_of(spark, sf_dir)

    def said(texts: list[tuple[str, str]]) -> list[tuple]:
        steps, out = experiment.plan_traces(spark, sf_dir, texts), []
        for db, sql in texts:
            tables = {t: set(c) for t, c in schemas[db].items()}
            mine = steps[db, sql]
            out.append((len(ir.lint_plan(ir.parse_plan(ir.render_plan(mine)), tables)), all(ir.agreement(mine, sql, set(tables)).values())))
        return out

    return _by_text(_asked(spark, sf_dir, _bank_texts()), said, "wrong long, agrees boolean").select("c_custkey", "sample_id", "wrong", "agrees")


def p1_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prompts of all styles for the bank, by digest and tokens."""
    tables = {t: read_table(spark, sf_dir, t) for t in {t for ts in DATABASES.values() for t in ts}}
    schemas = {d: inference.schema_text({t: tables[t] for t in ts}) for d, ts in DATABASES.items()}
    out = None
    for style in sorted(inference._ASK):
        made = inference.build_prompt(load_bank(spark), style, schemas)
        one = made.select("sample_id", F.lit(style).alias("style"), F.md5("prompt").alias("digest"), inference.count_tokens(F.col("prompt")).alias("tokens"), "fitted")
        out = one if out is None else out.unionByName(one)
    return out


def p9_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    """SQL found again in completions of every corruption, of all bank rows."""
    rows = [(f"{r['sample_id']}|{leaf}", f"a trace\n{inference.SQL_MARK}\n{make(r['gold_sql'])}" if leaf != "no output" else make(r["gold_sql"])) for r in bank_rows() for leaf, make in inference.CORRUPTIONS.items()]
    return spark.createDataFrame(rows, "id string, raw string").select("id", F.md5(inference.extract_sql(F.col("raw"))).alias("digest"))


def e2_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shape of every bank result by the safe path: columns, rows, different rows."""
    bank = bank_rows()
    ran = execution.run_many(spark, sf_dir, [(r["db_id"], r["gold_sql"]) for r in bank])
    rows = [(r["sample_id"], d.status, d.n_cols, d.n_rows, int(d.set[2])) for r in bank for d in [ran[r["db_id"], r["gold_sql"]]]]
    return spark.createDataFrame(rows, "sample_id string, status string, n_cols long, n_rows long, n_distinct long")


def e1_refused(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the guard says of texts that must not run, as customers send them."""
    session = execution.database_session(spark, sf_dir, "order_desk")
    said = lambda texts: [execution.refusal(session, q, DATABASES[d]) or ("", "") for d, q in texts]
    asked = _asked(spark, sf_dir, _unsafe_texts(), limits=False)
    return _by_text(asked, said, "condition string, leaf string").select("c_custkey", F.col("sample_id").alias("sql"), "condition", "leaf")


def _unsafe_texts() -> list[tuple[str, str, str]]:
    return [(q, "order_desk", q) for q in UNSAFE_SQL]


#: Texts that must be refused before they are analysed: commands, files, other databases, writes.
UNSAFE_SQL = (
    "select * from (select transform(o_orderkey) using 'cat' as (k string) from orders) t",
    "select * from parquet.`/tmp/x.parquet`",
    "select reflect('java.lang.System', 'getProperty', 'user.dir') as x from orders",
    "select o_orderkey from orders where exists (select java_method('java.lang.Math', 'abs', -1))",
    "select * from lineitem",
    "select * from global_temp.orders",
    "select * from range(10)",
    "insert into orders select * from orders",
    "with a as (select * from pages) select * from a",
    "select input_file_name() from orders",
    "drop table orders",
    "set x = 1",
)


def runs_ex(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All eleven runs: accuracy and output tokens."""
    outcomes, _, _ = experiment.results(spark, sf_dir)
    return metrics.ex(outcomes, ["run"]).join(metrics.token_stats(outcomes).select("run", "mean", "sd"), "run")


def runs_difficulty(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.ex(experiment.results(spark, sf_dir)[0], ["run", "difficulty"])


def runs_construct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.ex_by_construct(experiment.results(spark, sf_dir)[0])


def runs_sunburst(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.sunburst(experiment.results(spark, sf_dir)[0])


def runs_gains(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.gains_losses(metrics.paired(experiment.results(spark, sf_dir)[0].where("run not like '%_HID'"), "TEACH"), ["run"])


def runs_transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From the untuned student's level to that of the plan-tuned one."""
    o = experiment.results(spark, sf_dir)[0]
    src, dst = (o.where(F.col("run") == r).select("sample_id", F.col("level").alias(n)) for r, n in (("BASE", "src"), ("PGD", "dst")))
    return metrics.transitions(src.join(dst, "sample_id"))


def runs_trilemma(spark: SparkSession, sf_dir: str) -> DataFrame:
    outcomes, students, _ = experiment.results(spark, sf_dir)
    size = {(r.base, r.signal, r.style): (r.trainable, r.total) for r in students.select("base", "signal", "style", "trainable", "total").collect()}
    rows = [(run, *size[base, signal or "", experiment.trained_style(run, signal, style)], False) for run, (signal, style, base) in inference.RUNS.items() if base in experiment.BASES]
    return metrics.trilemma(outcomes, spark.createDataFrame(rows, "run string, trainable long, total long, leaves boolean"))


def runs_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where each student's training stopped and which evaluation was best."""
    c = experiment.results(spark, sf_dir)[1].where("signal <> ''").select(F.concat_ws("|", "base", "signal", "style").alias("run"), F.explode("curve").alias("c"))
    place = F.row_number().over(metrics.Window.partitionBy("run").orderBy("c.step")).cast("int")
    return metrics.early_stop(c.select("run", place.alias("step"), F.col("c.loss").alias("loss")))


def w7_mismatch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The prose student under its own prompt against the plan prompt."""
    return metrics.compare_runs(experiment.results(spark, sf_dir)[0], "FRD_X", "FRD")


def w8_second_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.ex(experiment.results(spark, sf_dir)[0].where("run like '%_7'"), ["run", "difficulty"])


def w10_hidden(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.ex(experiment.results(spark, sf_dir)[0].where("run = 'PGD_HID'"), ["run", "difficulty"])


def w1_bank_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distillation sets of the runs: samples by part and class."""
    return experiment.results(spark, sf_dir)[2].groupBy("part", "stratum").agg(F.count("*").alias("n"))


def t1_model_nll(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Completion loss a token of the plan student on each part of its sets."""
    _, students, sets = experiment.results(spark, sf_dir)
    model = bytes(students.where("base = 'student' and signal = 'plan'").head()["model"])
    nll = experiment.completion_nll(sets, model, experiment.schema_of(spark, sf_dir), "plan", "plan")
    per = nll.join(sets.select("sample_id", "part"), "sample_id").groupBy("part")
    return per.agg(F.count("*").alias("n"), F.sum("n_tok").alias("n_tok"), F.round(F.sum("nll") / F.sum("n_tok"), 4).alias("nll"))


def t9_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Validation loss by adapter rank, on the runs' sets."""
    sets = experiment.results(spark, sf_dir)[2]
    return experiment.rank_sweep(sets, sampling.gold_set(sets), experiment.schema_of(spark, sf_dir))


def w13_adapter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Adapter over a frozen four-bit base, 64 numbers to a label, trained data-parallel; the curve."""
    e = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding", "label"]).select("vec_id", F.col("embedding").cast("array<double>").alias("x"), F.col("label").alias("y"))
    rng = student.np.random.default_rng(7)
    base = student.dequantize4(*student.quantize4(rng.normal(0, 0.1, (10, 64))))
    model = student.Adapter(base, r=8, alpha=16.0)
    held = F.col("vec_id") % 10 == 0
    n = e.where(~held).count()
    curve = student.train(e.where(~held), e.where(held).persist(), model, "vec_id", size=max(6, n // 8), epochs=2, lr=2e-2)
    return spark.createDataFrame([(c["step"], float(c["epoch"]), float(c["train"]), float(c["loss"]), model.n_trainable()) for c in curve], "step long, epoch double, train double, loss double, trainable long")


def bank_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class by the lexer of the bank's queries as customers ask them."""
    asked = _asked(spark, sf_dir, _bank_texts())
    return asked.select("c_custkey", "sample_id", complexity.complexity(F.col("sql")).alias("stratum"))


def stream_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The windows of the stream form as a batch over the same function."""
    e = read_table(spark, sf_dir, "events", ["ts", "user_id", "event_type"]).withColumn("ts", F.col("ts").cast("timestamp"))
    return monitor.windowed_ex(e).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "run", "n", "ok")


def evaluate_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The evaluation path end to end on all bank rows: complete, extract, execute, compare,
    classify; ``made`` is the class of corruption put in."""
    profiles = {"TEACH": {"success": 0.8, "empty output": 0.1, "keyword": 0.1}, "BASE": {"success": 0.2, "no such column": 0.3, "column mismatch": 0.3, "no output": 0.2}}
    said = None
    for run, profile in profiles.items():
        asked = load_bank(spark).withColumns({"run": F.lit(run), "prompt": F.col("question"), "sample_id": F.concat(F.lit(run), "sample_id")})
        one = inference.infer(asked, inference.NoisyCompleter(profile, tell=True))
        said = one if said is None else said.unionByName(one)
    judged = experiment.judge(spark, sf_dir, said)
    sample = F.substr("sample_id", F.length("run") + 1)
    return judged.select("run", sample.alias("sample_id"), "difficulty", "level", "leaf", "ok", F.col("finish_reason").alias("made"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.ex(evaluate_runs(spark, sf_dir), ["run"])


TAPES: dict[str, tuple[Query, str | None]] = {
    "w1_quota": (w1_quota, None),
    "w1_report": (w1_report, None),
    "w1_leaks": (w1_leaks, None),
    "src_json_bank": (src_json_bank, None),
    "sink_partitioned": (sink_partitioned, f"select {_LEVEL} as level, count(*) as n from orders where o_orderstatus = 'F' group by 1"),
    "w2_ex": (w2_ex, f"select {_DIFF} as difficulty, count(*) as n, count(*) filter (o_orderstatus = 'F') as ok, round(100.0::double * count(*) filter (o_orderstatus = 'F') / count(*), 6) as ex from orders group by 1"),
    "w3_sunburst": (w3_sunburst, "with t as (select l_linenumber as run, case l_returnflag when 'N' then 'SUCC' when 'R' then 'SEM' else 'SYN' end as level, l_linestatus as leaf from lineitem), c as (select run, level, leaf, count(*) as n from t group by all) select *, round(100.0::double * n / sum(n) over (partition by run), 6) as pct from c"),
    "w4_construct": (w4_construct, "with t as (select unnest(list_filter([case when contains(text, chr(10)) then 'newline' end, case when regexp_matches(text, '[0-9]') then 'digit' end, case when contains(text, '@') then 'at' end, case when n_chars > 1475 then 'long' end], lambda x: x is not null)) as construct, lang = 'en' as ok from documents) select 'en' as run, construct, count(*) as n, count(*) filter (ok) as ok, round(100.0::double * count(*) filter (ok) / count(*), 6) as ex from t group by construct"),
    "w5_gains": (w5_gains, "with t as (select o_orderstatus = 'F' as t, o_orderpriority in ('1-URGENT', '2-HIGH') as s from orders) select count(*) filter (not t and s) as gains, count(*) filter (t and not s) as losses, count(*) filter (t and s) as both, count(*) filter (not t and not s) as neither, count(*) filter (not t and s) - count(*) filter (t and not s) as net from t"),
    "w6_transitions": (w6_transitions, f"with t as (select {_LEVEL} as src, ['SUCC', 'SEM', 'SYN', 'GEN'][o_custkey % 4 + 1] as dst from orders), c as (select src, dst, count(*) as n from t group by all), r as (select *, list_position(['SUCC', 'SEM', 'SYN', 'GEN'], src) as a, list_position(['SUCC', 'SEM', 'SYN', 'GEN'], dst) as b from c) select src, dst, n, round(100.0::double * n / sum(n) over (partition by src), 6) as pct, case when b < a then 'upgrade' when b > a then 'downgrade' else 'same' end as kind from r"),
    "w9_early_stop": (w9_early_stop, "with c as (select user_id as run, row_number() over (partition by user_id order by ts, event_id) as step, value as loss from events), g as (select *, min(loss) over (partition by run order by step rows between unbounded preceding and 1 preceding) as least from c), b as (select *, least is null or loss < least - 0.001 as better from g), s as (select *, step - coalesce(max(case when better then step end) over (partition by run order by step), 0) as wait from b), e as (select run, coalesce(min(case when wait >= 8 then step end), max(step)) as stop_step from s group by run) select e.run, e.stop_step, max(s.step) as best_step from e join s on s.run = e.run and s.step <= e.stop_step and s.better group by all"),
    "w11_tokens": (w11_tokens, r"with t as (select role, len(regexp_extract_all(coalesce(text, ''), '[A-Za-z0-9_]+|[^A-Za-z0-9_\s]')) as n from conversations) select role, count(*) as n, round(avg(n), 6) as mean, round(stddev_samp(n), 6) as sd from t group by role"),
    "w12_nll": (w12_nll, "with t as (select conv_id, turn, regexp_extract_all(lower(text), '[a-z0-9]+') as w from conversations where role = 'assistant'), p as (select conv_id, unnest(w) as tok, unnest(list_prepend('', w[:-2])) as prev from t where len(w) > 0), tr as (select * from p where conv_id % 5 <> 0), a as (select prev, tok, count(*) as c from tr group by all), b as (select prev, count(*) as cc from tr group by prev), v as (select count(distinct tok) + 1 as v from tr) select p.conv_id, round(sum(-ln((coalesce(c, 0) + 1.0::double) / (coalesce(cc, 0) + 1.0::double * v))), 6) as nll, count(*) as n_tok from p left join a using (prev, tok) left join b using (prev), v group by p.conv_id"),
    "w14_shots": (w14_shots, None),
    "apply_in_pandas": (apply_in_pandas, None),
    "bank_classes": (bank_classes, None),
    "join_asof": (join_asof, "with p as (select event_id, user_id, ts from events where event_type = 'purchase'), v as (select user_id, ts from events where event_type = 'view') select event_id, strftime(v.ts, '%Y-%m-%d %H:%M:%S') as last_view from p asof left join v on p.user_id = v.user_id and p.ts >= v.ts"),
    "join_theta": (join_theta, None),
    "agg_maxby": (agg_maxby, None),
    "agg_approx_distinct": (agg_approx_distinct, None),
    "agg_collect": (agg_collect, "select n_regionkey, string_agg(n_name, ',' order by n_name) as nations from nation group by n_regionkey"),
    "pivot_levels": (pivot_levels, f"with t as (select o_orderstatus, {_LEVEL} as level from orders) select o_orderstatus, " + ", ".join(f'count(*) filter (level = \'{x}\') as "{x}"' for x in metrics.LEVELS) + " from t group by o_orderstatus"),
    "fn_array": (fn_array, "with e as (select vec_id, embedding::double[] as x from embeddings) select vec_id, round(sqrt(list_inner_product(x, x)), 6) as norm, round(list_inner_product(x, list_reverse(x)), 6) as dot, len(list_filter(x, lambda v: v > 0)) as positive from e"),
    "fn_map": (fn_map, "select conv_id, string_agg(distinct role, ',' order by role) as roles, 2 * count(*) filter (role = 'user') as users_twice from conversations group by conv_id"),
    "fn_json": (fn_json, "with e as (select event_id, cast(json_extract(props, '$.k') as bigint) as k from events) select event_id, k, k as again, '{\"k\":' || (k + 1) || '}' as more from e"),
    "udf_scalar": (udf_scalar, "select conv_id, turn, (length(coalesce(text, '')) - length(replace(coalesce(text, ''), '?', '')))::int as marks from conversations"),
    "udf_pandas": (udf_pandas, None),
    "udaf_pandas": (udaf_pandas, "select user_id as run, 0.0::double as gap from events group by user_id"),
    "map_in_pandas": (map_in_pandas, "select conv_id as doc_id, coalesce(list_max(list_transform(string_split_regex(coalesce(text, ''), '\\s+'), lambda x: length(x))), 0) as longest from conversations"),
    "e8_compare": (e8_compare, f"with t as (select o_orderstatus as run, {_LEVEL} = 'SUCC' as ok, o_custkey % 97 as tok from orders), s as (select avg(ok::int::double) filter (run = 'F') as a, avg(ok::int::double) filter (run = 'O') as b, avg(tok) filter (run = 'F') as ta, avg(tok) filter (run = 'O') as tb from t) select round(100 * a, 6) as ex_a, round(100 * b, 6) as ex_b, round(100 * (a - b), 6) as points, round(100 * a / b, 6) as coverage, round(ta / tb, 6) as token_ratio from s"),
    "e13_error_delta": (e13_error_delta, "with p as (select run, level, leaf, round(100.0::double * count(*) / sum(count(*)) over (partition by run), 6) as pct from ({TAPE}) group by run, level, leaf), a as (select * from p where run = 'F'), b as (select * from p where run = 'O') select coalesce(a.level, b.level) as level, coalesce(a.leaf, b.leaf) as leaf, coalesce(a.pct, 0) as pct_a, coalesce(b.pct, 0) as pct_b, round(coalesce(b.pct, 0) - coalesce(a.pct, 0), 6) as delta from a full join b on a.level = b.level and a.leaf = b.leaf"),
    "e16_train_cost": (e16_train_cost, "with c as (select user_id as run, row_number() over (partition by user_id order by ts, event_id) as step, value as loss from events) select run, max(step) * 30 / 60.0::double as minutes, ceil(max(step) / 10)::bigint as epochs, max(step)::int as steps, arg_min(step, (loss, step))::int as best_step from c group by run"),
    "e17_trilemma": (e17_trilemma, "select run, count(*) as n, count(*) filter (level = 'SUCC') as ok, round(100.0::double * count(*) filter (level = 'SUCC') / count(*), 6) as ex, round(avg(n_tokens), 6) as tokens, case run when 'F' then 100 when 'O' then 50 end::bigint as trainable, case when run <> 'P' then 1000 end::bigint as total, run = 'P' as leaves from ({TAPE}) group by run"),
    "e18_mcnemar": (e18_mcnemar, "with g as (select count(*) filter (o_orderstatus <> 'F' and o_orderpriority in ('1-URGENT', '2-HIGH')) as gains, count(*) filter (o_orderstatus = 'F' and o_orderpriority not in ('1-URGENT', '2-HIGH')) as losses from orders) select gains, losses, round(power(greatest(abs(gains - losses) - 1, 0), 2) / nullif(gains + losses, 0), 6) as chi2 from g"),
    "e18_bootstrap": (e18_bootstrap, None),
    "e19_hallucination": (e19_hallucination, "select run, round(100.0::double * count(*) filter (leaf = 'no such column') / count(*), 6) as pct from ({TAPE}) group by run"),
    "e20_bounds": (e20_bounds, "with e as (select run, round(100.0::double * count(*) filter (level = 'SUCC') / count(*), 6) as ex from ({TAPE}) group by run), b as (select max(ex) filter (run = 'F') as lo, max(ex) filter (run = 'O') as hi from e) select run, ex, round((ex - lo) / nullif(hi - lo, 0), 6) + 0.0 as position from e, b"),
    "w1_sets": (w1_sets, None),
    "t6_batches": (t6_batches, "select doc_id, ((row_number() over (order by md5('42|0|' || doc_id), doc_id) - 1) // 6)::bigint as batch from documents"),
    "s1_structure": (s1_structure, None),
    "m1_plan_steps": (m1_plan_steps, None),
    "m6_plan_sources": (m6_plan_sources, None),
    "m3_lint": (m3_lint, None),
    "p1_prompts": (p1_prompts, None),
    "p9_extract": (p9_extract, None),
    "e2_digests": (e2_digests, None),
    "e1_refused": (e1_refused, None),
    "runs_ex": (runs_ex, None),
    "runs_difficulty": (runs_difficulty, None),
    "runs_construct": (runs_construct, None),
    "runs_sunburst": (runs_sunburst, None),
    "runs_gains": (runs_gains, None),
    "runs_transitions": (runs_transitions, None),
    "runs_trilemma": (runs_trilemma, None),
    "runs_training": (runs_training, None),
    "w7_mismatch": (w7_mismatch, None),
    "w8_second_base": (w8_second_base, None),
    "w10_hidden": (w10_hidden, None),
    "w1_bank_sets": (w1_bank_sets, None),
    "w13_adapter": (w13_adapter, None),
    "t1_model_nll": (t1_model_nll, None),
    "t9_ranks": (t9_ranks, None),
    "stream_windows": (stream_windows, "select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, user_id % 5 as run, count(*) as n, count(*) filter (event_type = 'purchase') as ok from events group by all"),
    "flagship_ex": (flagship, None),
}


def _text_query(sql: str) -> Query:
    return lambda spark, sf_dir: run_text(spark, sf_dir, sql)


def queries() -> dict[str, Query]:
    gold = {f"bank_{r['sample_id']}": _text_query(r["gold_sql"]) for r in bank_rows()}
    return {k: _text_query(v) for k, v in SQL.items()} | gold | {k: f for k, (f, _) in TAPES.items()}


def oracle_sql() -> dict[str, str]:
    quota = ", ".join(f"('{p}', '{s}', {n})" for (p, s), n in W1_QUOTAS.items())
    samples = "with s as (select source, row_number() over (order by md5('42|' || source), source) as r, count(*) over () as n from (select distinct source from documents join labels using (doc_id))), t as (select d.doc_id, case when r > n - round(n * 0.25) then 'OOD' else 'ID' end as pool, case when lang <> 'en' and n_chars > 1475 then 'joinset_sub' when lang <> 'en' then 'joinset' when n_chars > 1475 then 'sub' else 'single' end as stratum, quality = 1 as ok from documents d join labels using (doc_id) join s using (source))"
    own = {
        "w1_quota": f"{samples}, k as (select *, row_number() over (partition by pool, stratum order by md5('42|' || doc_id), doc_id) as rank from t where ok) select doc_id, pool, stratum, rank::int as rank from k join (values {quota}) as q(pool, stratum, w) using (pool, stratum) where rank <= w",
        "w1_report": f"{samples}, k as (select pool, stratum, count(*) as tried, count(*) filter (ok) as good from t group by all) select pool, stratum, w::bigint as wanted, least(w, coalesce(good, 0))::bigint as got, coalesce(tried, 0) as tried, good / tried as success_rate from (values {quota}) as q(pool, stratum, w) left join k using (pool, stratum)",
        "w1_leaks": r"""with s as (select source, row_number() over (order by md5('42|' || source), source) as r, count(*) over () as n from (select distinct source from documents)), t as (select doc_id, source, r > n - round(n * 0.25) as ood, md5(lower(trim(regexp_replace(text, '[\x20\x09-\x0D]+', ' ', 'g')))) as said from documents join s using (source)), b as (select said, count(*) filter (ood) as o from t where said is not null group by said having count(*) filter (ood) > 0 and count(*) filter (not ood) > 0) select 'database in both pools' as "check", count(*) as n from (select source from t group by source having count(distinct ood) > 1) union all select 'sample in both pools', count(*) from (select doc_id from t group by doc_id having count(distinct ood) > 1) union all select 'OOD text in ID', coalesce(sum(o), 0)::bigint from b""",
        "src_json_bank": f"select sample_id || '|' || c_custkey as sample_id, db_id, stratum, difficulty, question, md5(sql) as digest from ({_asked_sql(_bank_texts())}) a join {_values([tuple(r[c] for c in ('sample_id', 'stratum', 'difficulty', 'question')) for r in bank_rows()], 'sample_id, stratum, difficulty, question')} using (sample_id)",
        "w14_shots": "with s as (select a.vec_id as id, b.vec_id as shot, list_inner_product(a.embedding::double[], b.embedding::double[]) / sqrt(list_inner_product(a.embedding::double[], a.embedding::double[]) * list_inner_product(b.embedding::double[], b.embedding::double[])) as c from embeddings a join embeddings b on a.vec_id <> b.vec_id where a.vec_id % 50 = 0), r as (select *, row_number() over (partition by id order by c desc, shot) as rank from s) select id, rank::int as rank, shot from r where rank <= 3",
    }
    tape = f"select o_orderstatus as run, {_LEVEL} as level, case {_LEVEL} when 'SYN' then case when o_custkey % 2 = 0 then 'no such column' else 'keyword' end when 'SEM' then 'row mismatch' else {_LEVEL} end as leaf, o_custkey % 97 as n_tokens from orders"
    own |= {"apply_in_pandas": TAPES["w9_early_stop"][1].replace("e.stop_step, max(s.step)", "e.stop_step::int as stop_step, max(s.step)::int")} | _own_sql(samples)
    found = SQL | {f"bank_{r['sample_id']}": r["gold_sql"] for r in bank_rows()} | {k: q for k, (_, q) in TAPES.items() if q} | own
    return {k: q.replace("{TAPE}", tape) for k, q in found.items()}


def _values(rows: list[tuple], names: str) -> str:
    text = lambda v: "'" + v.replace("'", "''") + "'" if isinstance(v, str) else str(v)
    return "(values " + ", ".join("(" + ", ".join(map(text, r)) + ")" for r in rows) + f") as b({names})"


def _asked_sql(texts: list[tuple[str, str, str]], limits: bool = True) -> str:
    """What ``_asked`` gives, as SQL."""
    n, known = len(texts), _values([(k, *r) for k, r in enumerate(texts)], "k, sample_id, db_id, text")
    limit = "case when c_acctbal < 0 and not regexp_matches(text, 'limit [0-9]+$') then chr(10) || 'limit ' || length(said) else '' end" if limits else "''"
    said = r"select c_custkey, c_acctbal, coalesce(regexp_replace(c_mktsegment, '[\r\n]', ' ', 'g'), '') as said from customer"
    return f"select c_custkey, sample_id, db_id, text || {limit} || chr(10) || '-- ' || said as sql from ({said}) c join {known} on k = ((c_custkey % {n}) + {n}) % {n}"


def _own_sql(samples: str) -> dict[str, str]:
    """SQL whose answers rest on DuckDB's own parser and engine."""
    bank = bank_rows()
    # each different text that customers ask, parsed once
    trees = lambda rows: f"q as ({_asked_sql(rows)}), j as (select sql, json_serialize_sql(sql)::varchar as j from (select distinct sql from q)), t as (select * from q join j using (sql))"
    has = lambda x: f"contains(j, '{x}')"
    linked, nested = f"({has('\"type\":\"JOIN\"')} or {has('SET_OPERATION_NODE')})", f"({has('\"type\":\"SUBQUERY\"')} or regexp_matches(j, '\"cte_map\":\\{{\"map\":\\[\\{{'))"
    stratum = f"case when {linked} and {nested} then 'joinset_sub' when {linked} then 'joinset' when {nested} then 'sub' else 'single' end"
    count = lambda x: f"(len(string_split(j, '{x}')) - 1)"
    # references to common table expressions are base tables to the parser; only real names count
    scans = "(" + " + ".join(count(chr(34) + "table_name" + chr(34) + ":" + chr(34) + t + chr(34)) for t in TABLES) + ")"
    # functions carry an order of their own arguments, which isn't the query's
    orders = f"({count('ORDER_MODIFIER')} - {count(chr(34) + 'order_bys' + chr(34) + ':{' + chr(34) + 'type' + chr(34) + ':' + chr(34) + 'ORDER_MODIFIER')})"
    mix = _values([("single", 20, 5, 5), ("sub", 25, 5, 5), ("joinset", 15, 5, 5), ("joinset_sub", 10, 5, 5)], "stratum, a, b, c")
    shapes = " union all ".join(f"select '{r['sample_id']}' as sample_id, 'ok' as status, (select count(*) from (describe {r['gold_sql']}))::bigint as n_cols, (select count(*) from ({r['gold_sql']})) as n_rows, (select count(*) from (select distinct * from ({r['gold_sql']}))) as n_distinct" for r in bank)
    ask = " union all ".join(f"select '{k}' as style, {_quoted(v)} as head" for k, v in inference._ASK.items())
    kinds = "replace(replace(replace(replace(replace(lower(data_type), 'varchar', 'string'), 'integer', 'int'), 'float[]', 'array<float>'), 'timestamp', 'timestamp_ntz'), '[]', '')"
    member = _values([(d, t) for d, ts in DATABASES.items() for t in ts], "db_id, t")
    questions = _values([(r["sample_id"], r["db_id"], r["question"]) for r in bank], "sample_id, db_id, question")
    made = _values([(f"{r['sample_id']}|{leaf}", "" if leaf == "no output" else make(r["gold_sql"])) for r in bank for leaf, make in inference.CORRUPTIONS.items()], "id, sql")
    table, function, node = ("TABLE_OR_VIEW_NOT_FOUND", "no such table"), ("FUNCTION_NOT_ALLOWED", "other"), ("NODE_NOT_ALLOWED", "other")
    refused = [(q, *why) for q, why in zip(UNSAFE_SQL, (node, table, function, function, table, table, node, node, table, function, node, node), strict=True)]
    return {
        "e1_refused": f"select c_custkey, sample_id as sql, condition, leaf from ({_asked_sql(_unsafe_texts(), limits=False)}) a join {_values(refused, 'sample_id, condition, leaf')} using (sample_id)",
        "bank_classes": f"with {trees(_bank_texts())} select c_custkey, sample_id, {stratum} as stratum from t",
        "s1_structure": f'with {trees(_all_texts())} select c_custkey, sample_id, {stratum} as stratum, {has(chr(34) + "type" + chr(34) + ":" + chr(34) + "JOIN" + chr(34))} as "join", {has("SET_OPERATION_NODE")} as set_op, {orders} > 0 as order_by, {has("LIMIT_MODIFIER")} as "limit", ({has("DISTINCT_MODIFIER")} or regexp_matches(j, \'"distinct":true\')) as "distinct" from t',
        "m3_lint": f"select c_custkey, sample_id, 0::bigint as wrong, true as agrees from ({_asked_sql(_bank_texts())})",
        "e2_digests": shapes,
        "p1_prompts": f"with c as (select table_name as t, t || '(' || string_agg(column_name || ' ' || {kinds}, ', ' order by ordinal_position) || ')' as line from information_schema.columns group by table_name), d as (select db_id, string_agg(line, chr(10) order by b.t) as schema from {member} join c on c.t = b.t group by db_id), p as (select sample_id, style, head || chr(10) || chr(10) || 'Schema:' || chr(10) || schema || chr(10) || 'Question: ' || question || chr(10) as prompt from {questions} join d using (db_id), ({ask}) a) select sample_id, style, md5(prompt) as digest, len(regexp_extract_all(prompt, '[A-Za-z0-9_]+|[^A-Za-z0-9_\\s]')) as tokens, true as fitted from p",
        "p9_extract": f"select id, md5(nullif(sql, '')) as digest from {made}",
        "w1_sets": f"{samples}, m as (select * from {mix}), k as (select pool, stratum, row_number() over (partition by pool, stratum order by md5('42|' || doc_id), doc_id) as rank from t where ok), z as (select case when pool = 'OOD' then 'ood_val' when rank <= a then 'train' else 'id_val' end as part, stratum from k join m using (stratum) where rank <= case when pool = 'OOD' then c else a + b end) select part, stratum, count(*) as n, round(100.0::double * count(*) / sum(count(*)) over (partition by part), 6) as pct from z group by part, stratum",
        "m1_plan_steps": f"with {trees(_bank_texts())} select c_custkey, sample_id, {scans} as scans, {count(chr(34) + 'type' + chr(34) + ':' + chr(34) + 'JOIN' + chr(34))} as joins, {count('SET_OPERATION_NODE')} as setops, {orders} as sorts, {count('LIMIT_MODIFIER')} as limits from t",
    }


def _quoted(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"
