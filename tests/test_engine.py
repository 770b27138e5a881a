"""Plans, sampling, execution, measures and student against independent answers."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from plandistill import workloads
from plandistill.operators import execution, experiment, inference, language, metrics, relational, sampling, student
from plandistill.plans import complexity, ir
from plandistill.sources import tables
from plandistill.streaming import monitor


def test_bank_traces_and_classes(spark, sf):
    tables.register(spark, sf)
    for r in tables.bank_rows():
        steps = ir.plan_ir(spark, r["gold_sql"])
        assert [vars(s) for s in ir.parse_plan(ir.render_plan(steps))] == [vars(s) for s in steps]
        assert ir.lint_plan(steps, set(tables.TABLES)) == [], r["sample_id"]
        assert complexity.exact_complexity(spark, r["gold_sql"]) == r["stratum"]
        assert ir.render_prose(steps, "a") == ir.render_prose(steps, "a")
    with pytest.raises(ValueError):
        ir.parse_plan("look at the table")
    assert ir.lint_plan([ir.Step(1, "FLY", [2])]) == ["step 1: unknown operation FLY", "step 1: input 2 is not an earlier step"]


@pytest.mark.parametrize("name", ["w1_quota", "w1_leaks", "src_json_bank", "sink_partitioned", "w2_ex", "w5_gains", "w6_transitions", "w9_early_stop", "w12_nll", "bank_classes", "join_full", "bank_q46", "s1_structure", "m1_plan_steps", "m3_lint", "p1_prompts", "p9_extract", "w1_sets", "t6_batches", "e13_error_delta", "e17_trilemma", "join_asof", "apply_in_pandas"])
def test_queries_equal_sql(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for t in tables.TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = workloads.queries()[name](spark, sf)
    cols = sorted(df.columns)
    rel = con.execute(workloads.oracle_sql()[name])
    at = [[d[0] for d in rel.description].index(c) for c in cols]
    plain = lambda v: v if isinstance(v, (str, bool, type(None))) else float(v)
    assert sorted(str([plain(r[i]) for i in at]) for r in rel.fetchall()) == sorted(str([plain(v) for v in r]) for r in df.select(*cols).collect())


def test_pools_share_no_table():
    pools = sampling.component_pools(tables.DATABASES)
    assert sorted(d for d, p in pools.items() if p == "OOD") == ["chat_log", "corpus_quality", "web_archive"]
    side = lambda p: {t for d, q in pools.items() if q == p for t in tables.DATABASES[d]}
    assert not side("ID") & side("OOD")


def test_waves_equal_full_ranking(spark, sf):
    samples = workloads.w1_samples(spark, sf).select("doc_id", "pool", "stratum", "success")
    quotas = {("ID", "sub"): 5, ("ID", "single"): 4, ("OOD", "sub"): 10_000}
    want = {tuple(r) for r in sampling.sample_quota(samples, quotas, "doc_id").select("doc_id", "rank").collect()}
    done = lambda rows: rows.join(samples.select("doc_id", "success"), "doc_id")
    got = sampling.generate_until(samples.drop("success"), done, quotas, "doc_id", wave=1.2)
    assert {tuple(r) for r in got.select("doc_id", "rank").collect()} == want
    assert sum(sampling.scale_quotas(48).values()) == 48 and sampling.scale_quotas(1000) == {s: v[0] for s, v in sampling.MIX.items()}


def test_every_leaf(spark, sf):
    gold = "select o_orderstatus, count(*) as n from orders group by o_orderstatus"
    top = "select o_orderkey, o_custkey from orders order by o_orderkey limit 5"
    cases = [
        ("select nope from orders", gold, "SYN", "no such column"), ("select x.o_orderkey from orders", gold, "SYN", "no such column"), ("select * from nope", gold, "SYN", "no such table"), ("select * from pages", gold, "SYN", "no such table"),
        ("selct * from orders", gold, "SYN", "keyword"), ("select o_orderkey from from orders", gold, "SYN", "keyword"), ("select o_orderkey from orders where", gold, "SYN", "keyword"),
        ("select o_orderkey from orders limit 3 where o_orderkey > 1", gold, "SYN", "clause order"), ("select sum(o_orderkey from orders", gold, "SYN", "clause order"), ("select o_orderkey from orders order o_orderkey by", gold, "SYN", "clause order"),
        ("select o_orderkey, count(*) from orders", gold, "SYN", "other"), ("select nosuchfn(o_orderkey) from orders", gold, "SYN", "other"), ("select 1/0 from orders", gold, "SYN", "other"), ("drop table orders", gold, "SYN", "other"),
        ("select o_orderstatus, count(*) as n, 1 as x from orders group by o_orderstatus", gold, "SEM", "column mismatch"), (top.replace("5", "4"), top, "SEM", "row mismatch"), ("select o_orderkey from orders order by o_orderkey limit 4", top, "SEM", "row & column mismatch"),
        (gold.replace("count(*)", "count(*) + 1"), gold, "SEM", "value mismatch"), (gold.replace("group", "where 1 = 0 group"), gold, "SEM", "empty output"), ("select o_orderstatus as s, sum(1) as k from orders group by 1 order by 2", gold, "SUCC", "success"),
    ]
    s = execution.database_session(spark, sf, "order_desk")
    for sql, g, level, leaf in cases:
        assert execution.outcome(execution.run_sql(s, sql), execution.run_sql(s, g)) == (level, leaf), sql
    assert execution.outcome(None, execution.run_sql(s, gold)) == ("GEN", "no output")


def test_digest_sees_what_rows_show(spark):
    a = spark.createDataFrame([(1, "x"), (2, None), (2, None)], "k int, v string")
    b = spark.createDataFrame([(2.0, None), (1.0, "x"), (2.0, None)], "other double, w string")
    one, two = execution.digest(a).head(), execution.digest(b).head()
    assert one == two and execution.same_rows(a, b)
    dup = execution.digest(a.distinct()).head()
    assert dup.bag_a != one.bag_a and dup.set_a == one.set_a and execution.same_rows(a, a.distinct(), "set")
    assert not execution.same_rows(a, a.na.fill(""))


def test_ordered_results_differ_by_position(spark, sf):
    s = execution.database_session(spark, sf, "order_desk")
    ask = lambda q: execution.run_sql(s, q, ordered=True)
    up, down = ask("select o_orderkey from orders order by o_orderkey"), ask("select o_orderkey from orders order by o_orderkey desc")
    again = ask("select o_orderkey as k from (select * from orders union all select * from orders where 1 = 0) order by k + 0")
    assert execution.same_result(up, down, "bag") and not execution.same_result(up, down, "ordered")
    assert execution.same_result(up, again, "ordered")
    for bad in (("sorted", up), ("ordered", execution.run_sql(s, "select o_orderkey from orders"))):
        with pytest.raises(ValueError):
            execution.same_result(up, bad[1], bad[0])


def test_extraction(spark):
    raw = ["STEP 1\n### SQL\nselect 1", "so\n```sql\nselect 2\n```", "thus select 3", "I cannot answer", "", None]
    got = [r[0] for r in spark.createDataFrame([(i, x) for i, x in enumerate(raw)], "i int, raw string").orderBy("i").select(inference.extract_sql(F.col("raw"))).collect()]
    assert got == ["select 1", "select 2", "select 3", None, None, None]


def test_printed_arithmetic(spark):
    rows = [("a", i, i < 225, 362) for i in range(500)] + [("b", i, i < 268, 99) for i in range(500)]
    df = spark.createDataFrame(rows, "run string, sample_id int, ok boolean, n_tokens int")
    r = metrics.compare_runs(df, "a", "b").head()
    assert round(r.ex_a, 1) == 45.0 and round(r.coverage, 1) == 84.0 and round(r.token_ratio, 2) == 3.66
    g = metrics.gains_losses(metrics.paired(df, "b")).head()
    assert g.net == 225 - 268


def test_early_stop_hand_curves(spark):
    curves = {1: [1 / s for s in range(1, 31)], 2: [5 - min(s, 5) for s in range(1, 31)], 3: [1 - 0.0005 * s for s in range(1, 31)]}
    rows = [(k, s, float(v)) for k, c in curves.items() for s, v in enumerate(c, 1)]
    got = {r.run: (r.stop_step, r.best_step) for r in metrics.early_stop(spark.createDataFrame(rows, "run int, step int, loss double")).collect()}
    assert got[2] == (13, 5) and got[3][0] in (9, 10, 11) and got[1][0] == 30


def test_quantised_base_and_adapter(spark):
    rng = np.random.default_rng(0)
    w = rng.normal(size=(10, 65))
    q = student.dequantize4(*student.quantize4(w))
    gap = np.diff(student.CODE).max() / 2
    assert np.abs(q - w).max() <= gap * np.abs(w).max() + 1e-6
    m = student.Adapter(q, r=4, alpha=8)
    assert np.allclose(m.merge(), q) and m.n_trainable() == 4 * 75
    x, y = rng.normal(size=(30, 65)), rng.integers(0, 10, 30)
    m.b = rng.normal(size=m.b.shape) * 0.1
    loss, ga, gb = m.loss_grad(x, y)
    for name, g in (("a", ga), ("b", gb)):
        v = getattr(m, name)
        v[1, 2] += 1e-5
        assert abs((m.loss_grad(x, y)[0] - loss) / 1e-5 - g[1, 2]) < 1e-2
        v[1, 2] -= 1e-5
    df = spark.createDataFrame([(i, x[i].tolist(), int(y[i])) for i in range(30)], "id int, x array<double>, y int").repartition(3)
    got = student.grad_step(df, m)
    assert abs(got[0] - loss) < 1e-8 and got[1] == 30 and np.allclose(got[2], ga) and np.allclose(got[3], gb)
    curve = student.train(df, df, student.Adapter(q, r=4, alpha=8), "id", size=15, epochs=1, lr=1e-2)
    assert len(curve) == 2 and curve[-1]["loss"] < curve[0]["loss"] + 0.1
    assert sorted(r["count"] for r in student.batches(df, 8, 0, "id").groupBy("batch").count().collect()) == [6, 8, 8, 8]


def test_shots_come_from_the_whole_table(spark, tmp_path):
    rng = np.random.default_rng(1)
    v = rng.normal(size=(1300, 5))
    v[1250] = v[50]  # a tie
    spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    want = set()
    for i in range(0, 1300, 50):
        near = np.round(unit @ unit[i], 12)
        near[i] = -2
        want |= {(i, r + 1, int(s)) for r, s in enumerate(np.lexsort((np.arange(1300), -near))[:3])}
    assert {tuple(r) for r in workloads.w14_shots(spark, str(tmp_path)).collect()} == want and any(s >= 1000 for _, _, s in want)


def test_greedy_decoding_repeats_what_it_saw():
    g = student.Greedy(["q1 step scan orders sql select a", "q2 step scan parts sql select b"])
    assert g.decode("q2 step") == "scan parts sql select b"


def test_flagship(spark, sf):
    got = {r.run: r.ok for r in workloads.flagship(spark, sf).collect()}
    assert got["TEACH"] > got["BASE"]


def test_evaluation_takes_the_whole_bank(spark, sf):
    got = workloads.evaluate_runs(spark, sf).collect()
    bank = {r["sample_id"] for r in tables.bank_rows()}
    assert sorted((r.run, r.sample_id) for r in got) == sorted((run, i) for run in ("TEACH", "BASE") for i in bank)
    level = lambda made: "SUCC" if made == "success" else "GEN" if made == "no output" else "SEM" if made in ("empty output", "column mismatch") else "SYN"
    assert [(r.sample_id, r.made, r.leaf, r.level) for r in got if (r.leaf, r.level) != (r.made, level(r.made))] == []


def test_stream_windows_equal_the_table(spark, sf):
    """All windows of the stream, read to the end in complete mode, are the batch's."""
    sink = monitor.windowed_ex(monitor.event_stream(spark, sf)).writeStream.format("memory").queryName("windows").outputMode("complete").trigger(availableNow=True).start()
    sink.awaitTermination(120)
    table = tables.read_table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    want = sorted(map(tuple, monitor.windowed_ex(table).collect()))
    assert want and sorted(map(tuple, spark.table("windows").collect())) == want


def test_leak_report_finds_planted_leaks(spark):
    rows = [("ID", "a", 1, "Count  the rows"), ("OOD", "b", 2, "count the\nrows "), ("OOD", "b", 3, "other"), ("ID", "c", 4, None), ("OOD", "c", 5, None), ("ID", "d", 6, "x"), ("OOD", "e", 6, "y")]
    df = spark.createDataFrame(rows, "pool string, db_id string, sample_id long, question string")
    assert {r["check"]: r.n for r in sampling.leak_report(df).collect()} == {"database in both pools": 1, "sample in both pools": 1, "OOD text in ID": 1}
    assert [r.n for r in sampling.leak_report(df.limit(0)).collect()] == [0, 0, 0]


def test_guard_refuses_wherever_it_stands(spark, sf, tmp_path):
    s = execution.database_session(spark, sf, "order_desk")
    db = tables.DATABASES["order_desk"]
    for q in workloads.UNSAFE_SQL:
        assert execution.refusal(s, q, db), q
    hit = tmp_path / "hit"
    bad = f"select * from (select transform(o_orderkey) using 'touch {hit}; cat' as (k string) from orders) t"
    assert execution.run_sql(s, bad, db).status == "error" and not hit.exists()
    nested = f"select c_name from customer where c_custkey in (select k from (select o_custkey as k from orders where exists (select 1 from parquet.`{sf}/pages.parquet`)) t)"
    assert execution.run_sql(s, nested, db).leaf == "no such table"
    fine = ["select /*+ broadcast(customer) */ count(*) from orders join customer on o_custkey = c_custkey", "values (1, 'a'), (2, 'b')", "with a as (select o_custkey as k from orders), b as (select * from a) select count(*) from b join customer on k = c_custkey"]
    assert [execution.run_sql(s, q, db).status for q in fine] == ["ok"] * 3
    for r in tables.bank_rows():
        assert execution.refusal(s, r["gold_sql"], tables.DATABASES[r["db_id"]]) is None, r["sample_id"]


def test_limits_are_errors_and_cut_nothing(spark, sf):
    s = execution.database_session(spark, sf, "order_desk")
    assert execution.run_sql(s, "select * from orders", max_rows=10).error == "ROW_CAP"
    assert execution.run_sql(s, "select * from orders limit 10", max_rows=10).n_rows == 10
    slow = "select count(*) from orders a cross join orders b cross join orders c cross join orders d where a.o_totalprice + b.o_totalprice + c.o_totalprice > d.o_totalprice"
    got = execution.run_sql(s, slow, seconds=2.0)
    assert (got.status, got.error, got.leaf) == ("error", "TIMEOUT", "other")
    assert execution.run_sql(s, "select count(*) from orders", seconds=60.0).status == "ok"


def test_numbers_compare_by_value(spark):
    one = lambda x, kind: execution.digest(spark.createDataFrame([(x,)], f"v {kind}")).head()
    from decimal import Decimal

    assert one(1e-7, "double") != one(4e-7, "double") and one(1e33, "double") == one(1e33, "double") != one(2e33, "double")
    assert one(2, "int") == one(2.0, "double") == one(Decimal("2.00"), "decimal(10,2)") and one(-0.0, "double") == one(0.0, "double")
    assert one(Decimal("0.1"), "decimal(10,2)") == one(0.1, "double") == one(0.1 + 1e-17, "double")
    assert one(9007199254740993, "long") != one(9007199254740992, "long") and one(float("nan"), "double") != one(None, "double")
    assert one(0.1 + 0.2, "double") == one(0.3, "double")
    assert execution.digest(spark.createDataFrame([(0.1 + 0.2,)], "v double"), digits=None).head() != execution.digest(spark.createDataFrame([(0.3,)], "v double"), digits=None).head()


def test_structure_equals_the_parser(spark):
    for name, q in workloads.ODD_SQL.items():
        found = complexity.structure(q)
        assert complexity._class(found) == complexity.exact_complexity(spark, q), name
    assert "order_by" not in complexity.structure(workloads.ODD_SQL["window"]) and "window" in complexity.structure(workloads.ODD_SQL["window"])


def test_plan_sources_and_lint_of_columns(spark, sf):
    s = execution.database_session(spark, sf, "order_desk")
    q = "with big as (select o_custkey as k, count(*) as n from orders group by o_custkey) select c_name from customer join big on k = c_custkey where n > 3 order by c_name limit 5"
    ops = {x: [t.op for t in ir.plan_ir(s, q, x)] for x in ("parsed", "analyzed", "optimized", "physical")}
    assert ops["parsed"].count("SCAN") == 2 and {"AGGREGATE", "JOIN", "FILTER", "SORT", "LIMIT"} <= set(ops["parsed"])
    assert ops["physical"].count("JOIN") == 1 and ops["physical"].count("AGGREGATE") == 1 and ops["physical"].count("SCAN") == 2
    schema = {"orders": {"o_custkey"}, "customer": {"c_name", "c_custkey"}}
    wrong = ir.lint_plan([ir.Step(1, "SCAN", [], "orders", ["o_custkey", "nope"]), ir.Step(2, "FILTER", [1], "x > 1", [], ["gone"])], schema)
    assert wrong == ["step 1: orders has no column nope"] + (["step 2: unknown column gone"] if "gone" not in {"o_custkey", "nope"} else [])
    long = "select " + ", ".join(f"o_orderkey + {i} as a_rather_long_name_for_column_{i}" for i in range(90)) + " from orders"
    assert "a_rather_long_name_for_column_89" in ir.render_plan(ir.plan_ir(s, long))


def test_admission_pairs_and_gold(spark):
    done = spark.createDataFrame([("a",), ("b",), ("c",)], "sample_id string")
    out = spark.createDataFrame([("a", "SUCC"), ("b", "SEM")], "sample_id string, level string")
    assert {r.sample_id: r.success for r in sampling.admit(done, out).collect()} == {"a": True, "b": False, "c": False}
    x, y = spark.createDataFrame([("a", "P")], "sample_id string, t string"), spark.createDataFrame([("a", "Q"), ("b", "Q")], "sample_id string, t string")
    p, q = sampling.pair_signals(x, y)
    assert p.count() == q.count() == 1 and sampling.pair_signals(x, y, paired=False)[1].count() == 2
    bank = spark.createDataFrame([("a", "ID"), ("b", "OOD")], "sample_id string, pool string")
    assert [r.sample_id for r in sampling.gold_set(bank).collect()] == ["a"]
    null = sampling.split_pools(spark.createDataFrame([(1, "x"), (2, None), (3, "y"), (4, "z"), (5, "w")], "k int, db_id string"))
    assert {r.k: r.pool for r in null.collect()}[2] == "ID" and null.count() == 5


def test_inference_caps_and_completers(spark):
    rows = [("a", "short prompt", "select 1", "STEP"), ("b", "w " * 30, "select 2", None), ("c", None, "select 3", None)]
    df = spark.createDataFrame(rows, "sample_id string, prompt string, gold_sql string, plan string")
    got = {r.sample_id: r for r in inference.infer(df, inference.EndpointCompleter(lambda p: "x " * 50), max_in=20, max_out=10).collect()}
    assert (got["a"].n_tokens, got["a"].finish_reason, got["b"].raw, got["b"].finish_reason) == (10, "length", "", "prompt too long")
    noisy = inference.infer(df, inference.NoisyCompleter({"success": 1.0})).select(inference.extract_sql(F.col("raw")).alias("s")).collect()
    assert sorted(r.s for r in noisy) == ["select 1", "select 2", "select 3"]
    kept = inference.infer(df, inference.ReplayCompleter(spark.createDataFrame([("a", "hi")], "sample_id string, raw string"))).collect()
    assert {r.sample_id: r.finish_reason for r in kept} == {"a": "end", "b": "missing", "c": "missing"}


def test_one_rule_of_early_stopping(spark):
    curves = [[1 - 0.0005 * s for s in range(30)], [3.0, 2.0, float("nan"), 1.0, 1.0] + [1.5] * 12, [1.0] * 5]
    rows = [(k, s, float(v)) for k, c in enumerate(curves) for s, v in enumerate(c, 1)]
    df = spark.createDataFrame(rows, "run long, step int, loss double")
    assert sorted(map(tuple, metrics.early_stop(df).collect())) == sorted(map(tuple, relational.early_stop_by_loop(df).collect()))


def test_levels_of_the_four_bit_code():
    c = student.CODE
    assert len(c) == 16 and c[0] == -1 and c[-1] == 1 and 0.0 in c and (np.diff(c) > 0).all()
    assert np.diff(c)[6:9].max() < np.diff(c)[0] and sum(c < 0) == 7  # finer near zero, as a normal is denser there


def test_student_gradients_loss_mask_and_copies():
    examples = [language.Example("plan", "How many in ASIA over 120?", "d", ["select", "'Q3", "Q5"]), language.Example("plan", "x", "d", ["select"])]
    s = language.Student(language.vocabulary([x.target for x in examples]), width=5, r=3, alpha=6.0)
    s.part = {k: v.astype(np.float64) + 0.1 for k, v in s.part.items()}
    s.base = {k: v.astype(np.float64) for k, v in s.base.items()}
    data = s.places(examples)
    loss, n, grads = s.loss_grad(data)
    assert n == 6  # completion tokens and an end each; no prompt token is a target
    for k in ("u_a", "u_b", "e_b"):
        s.part[k][1, 1] += 1e-4
        assert abs((s.loss_grad(data, grad=False)[0] - loss) / 1e-4 - grads[k][1, 1]) < 2e-2, k
        s.part[k][1, 1] -= 1e-4
    used, g = grads["e_a"]
    s.part["e_a"][used[0], 1] += 1e-4
    assert abs((s.loss_grad(data, grad=False)[0] - loss) / 1e-4 - g[0, 1]) < 2e-2
    q = "Customers in MIDDLE over 120?"
    names = language.slots({"customer": ["c_name", "c_nationkey"]})
    tokens = language.encode("select c_name from customer where r = 'MIDDLE' and n > 120", q, names)
    assert "T0" in tokens and "'Q2" in tokens and "Q4" in tokens
    assert language.decode(tokens, q, names) == "select c_name from customer where r = 'MIDDLE' and n > 120"


def test_student_learns_and_travels_packed():
    import pickle

    rows = [language.Example("direct", f"count {w}", "d", ["### SQL", "select", w, "from", "t"]) for w in ("red", "blue", "green", "black")]
    s = language.Student(language.vocabulary([x.target for x in rows])).quantise()
    before = s.nll(rows)[0]
    s.fit(rows * 6, rows, size=6, epochs=20, lr=1e-2)
    again = pickle.loads(pickle.dumps(s))
    assert s.nll(rows)[0] < before / 4 and all(again.greedy(x)[0] == x.target for x in rows)
    assert again.greedy(rows[0], language.Decode(max_out=2)) == (["### SQL", "select"], "length")


def test_bank_expansion_keeps_question_class_and_banks_apart(spark, sf):
    values = tables.domains(spark, sf)
    one = tables.expand_bank(tables.bank_rows(), values, 0)
    assert len(one) > 800 and len({r["sample_id"] for r in one}) == len(one) and len({r["question"] for r in one}) == len(one)
    stratum = {r["sample_id"]: r["stratum"] for r in tables.bank_rows()}
    assert all(complexity._class(complexity.structure(r["gold_sql"])) == stratum[r["sample_id"].split("_")[0]] for r in one)
    two = tables.expand_bank(tables.bank_rows(), values, 48, 43, {r["question"] for r in one[:300]})
    assert len(two) == 48 and not {r["question"] for r in two} & {r["question"] for r in one[:300]}


def test_sessions_of_a_stream_and_admission_by_arrival(spark, sf, tmp_path):
    events = tables.read_table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    want = {tuple(r) for r in monitor.session_ex(events).collect()}
    q = monitor.session_ex(monitor.event_stream(spark, sf)).writeStream.format("memory").queryName("sessions").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {tuple(r) for r in spark.table("sessions").collect()}
    assert got and got <= want  # sessions that the watermark has closed
    rows = [(f"s{i}", "single" if i % 3 else "sub", i % 4 != 0, f"2024-01-01 00:00:{i:02d}") for i in range(30)] + [("s1", "single", True, "2024-01-01 00:00:40")]
    spark.createDataFrame(rows, "sample_id string, stratum string, success boolean, t string").select("sample_id", "stratum", "success", F.to_timestamp("t").alias("ts")).coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("sample_id string, stratum string, success boolean, ts timestamp").parquet(f"{tmp_path}/in")
    q = monitor.stream_admit(stream, {"single": 5, "sub": 100}).writeStream.format("memory").queryName("admitted").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    out = [tuple(r) for r in spark.table("admitted").collect()]
    good = {r[0]: r[1] for r in rows if r[2]}
    assert len(out) == len(set(out)) and all(good[i] == k for k, i in out)
    assert sum(k == "single" for k, _ in out) == 5 and sum(k == "sub" for k, _ in out) == sum(k == "sub" for k in good.values())


def test_functions_in_sql(spark):
    from plandistill.functions import registry

    registry.register_functions(spark)
    r = spark.sql("select complexity_of('select * from a, b') as c, constructs_of('select count(*) from a limit 1') as k, extract_sql('x\n### SQL\nselect 1') as s, count_tokens('a b.c') as n").head()
    assert (r.c, r.k, r.s, r.n) == ("joinset", ["aggregate", "limit"], "select 1", 4)
    assert registry.plan_trace(spark, "select 1 as x where 2 > 1").startswith("STEP 1")


def test_runs_end_to_end(spark, sf):
    """All eleven runs on small sets: every question answered once, levels known, sets within quotas."""
    outcomes, students, sets = experiment.run_variants(spark, sf, total=24, n_dev=16)
    n = {r.run: r.n for r in metrics.ex(outcomes, ["run"]).collect()}
    assert n == dict.fromkeys(inference.RUNS, 16)
    assert {r.level for r in outcomes.select("level").distinct().collect()} <= set(metrics.LEVELS)
    assert {(r.base, r.signal) for r in students.collect()} == {("student", ""), ("student", "none"), ("student", "plan"), ("student", "prose"), ("second", ""), ("second", "plan"), ("second", "prose")}
    got = {(r.part, r.stratum): r["count"] for r in sets.groupBy("part", "stratum").count().collect()}
    assert sum(v for (p, _), v in got.items() if p == "train") == 24
    assert set(r.pool for r in sets.where("part = 'ood_val'").select("pool").distinct().collect()) == {"OOD"}


def test_shots_by_other_methods(spark):
    rng = np.random.default_rng(2)
    v = rng.normal(size=(300, 8))
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "id long, vector array<double>")
    q = df.where("id % 30 = 0")
    assert {(r.id, r.rank): r.shot for r in inference.select_shots(q, df, 2, "static").collect()}[0, 1] == 1
    exact = {(r.id, r.shot) for r in inference.select_shots(q, df, 3).collect()}
    near = {(r.id, r.shot) for r in inference.select_shots(q, df, 3, "lsh").collect()}
    assert len(near & exact) >= 0.6 * len(exact)
    with pytest.raises(ValueError):
        inference.select_shots(q, df, 3, "none")


def test_long_prompts_lose_their_oldest_shots(spark):
    q = spark.createDataFrame([("a", "d", "how many?")], "sample_id string, db_id string, question string")
    made = inference.build_prompt(q, "plan", {"d": "t(x int)"}, ["old " * 9_000, "mid " * 4_000, "new " * 4_000]).head()
    assert "old" not in made.prompt and "mid" in made.prompt and "new" in made.prompt and not made.fitted and "how many?" in made.prompt


def test_bootstrap_interval_holds_the_share(spark):
    df = spark.range(2000).select(F.lit("a").alias("run"), F.col("id").alias("sample_id"), (F.col("id") % 4 == 0).alias("ok"))
    r = metrics.bootstrap_ci(df).head()
    assert 21.5 < r.low < 25 < r.high < 28.5


def same_as_sql(spark, name, tables_):
    """A query over the tables given (name to frame) against its SQL in DuckDB, row by row."""
    import tempfile

    import duckdb

    con, d = duckdb.connect(), tempfile.mkdtemp()
    for t, df in tables_.items():
        df.coalesce(1).write.parquet(f"{d}/{t}.parquet")
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet/*.parquet'")
    df = workloads.queries()[name](spark, d)
    cols = sorted(df.columns)
    want = con.execute(f"select {', '.join(chr(34) + c + chr(34) for c in cols)} from ({workloads.oracle_sql()[name]})").fetchall()
    plain = lambda v: v if isinstance(v, (str, bool, type(None))) else float(v)
    got = df.select(*cols).collect()
    assert sorted(str([plain(v) for v in r]) for r in got) == sorted(str([plain(v) for v in r]) for r in want)
    return got, df


def test_near_pairs_meet_in_cells(spark):
    inf, nan = float("inf"), float("nan")
    prices = [900.0, 900.1, 901.0, 901.1, 900.9999999999999, 902.0, 0.0, -0.0, -0.5, -1.0, -1.5, 0.9999999999999999, 1.0, None, nan, nan, inf, inf, -inf, 1e300, 1e300, 4.611686018427388e18, 4.611686018427388e18, -9.3e18, -9.3e18]
    rows = [(i, b, p) for i, (b, p) in enumerate((b, p) for b in ("x", "y", None) for p in prices)] + [(None, "x", 900.0), (3, "x", 900.2)]
    got, df = same_as_sql(spark, "join_theta", {"part": spark.createDataFrame(rows, "p_partkey long, p_brand string, p_retailprice double")})
    assert len(got) > 30
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin [_by" in plan and "_meet" in plan  # rows meet by brand and cell, not by brand alone
    third = relational.near_pairs(spark.range(40).select(F.lit("a").alias("b"), "id", (F.col("id") * 0.1).alias("v")), "b", "id", "v", 0.3)
    assert {tuple(r) for r in third.collect()} == {(i, j) for i in range(40) for j in range(i + 1, 40) if abs(i * 0.1 - j * 0.1) < 0.3}


def test_largest_event_of_several_is_the_first(spark):
    nan = float("nan")
    rows = [(i, u, v) for i, (u, v) in enumerate([(1, 2.0), (1, 5.0), (2, nan), (2, 9.0), (2, nan), (3, None), (3, None), (1, 5.0), (4, -0.0), (4, 0.0), (None, 1.0), (None, 1.0), (5, None), (5, 0.5)] * 3)] + [(None, 1, 7.0), (None, 6, 1.0)]
    got, _ = same_as_sql(spark, "agg_maxby", {"events": spark.createDataFrame(rows, "event_id long, user_id long, value double")})
    assert {r.user_id: r.largest for r in got} == {1: 1, 2: 2, 3: None, 4: 8, None: 10, 5: 13, 6: None}
    parts = spark.createDataFrame(rows[::-1], "event_id long, user_id long, value double").repartition(7)
    again = parts.groupBy("user_id").agg(relational.first_max_by(F.col("event_id"), F.col("value")).alias("largest"))
    assert {r.user_id: r.largest for r in again.collect()} == {r.user_id: r.largest for r in got}


def test_train_cost_counts_steps_that_repeat_a_loss(spark):
    from datetime import datetime

    nan = float("nan")
    curves = {1: [3.0, 1.0, 2.0, 1.0, 3.0], 2: [nan, nan], 3: [None, None], 4: [None, nan, 4.0, None], 5: [0.0, -0.0] * 6, 6: [nan, None], None: [2.0, 2.0]}
    rows = [(100 * (run or 9) + k, run, datetime(2024, 1, 1, 0, k // 2), v) for run, c in curves.items() for k, v in enumerate(c)]
    got, _ = same_as_sql(spark, "e16_train_cost", {"events": spark.createDataFrame(rows, "event_id long, user_id long, ts timestamp_ntz, value double")})
    assert {r.run: (r.minutes, r.epochs, r.steps, r.best_step) for r in got} == {1: (2.5, 1, 5, 2), 2: (1.0, 1, 2, 1), 3: (1.0, 1, 2, 1), 4: (2.0, 1, 4, 3), 5: (6.0, 2, 12, 1), 6: (1.0, 1, 2, 1), None: (1.0, 1, 2, 1)}


CUSTOMERS = [(k, b, s) for k, (b, s) in enumerate([(1.0, "BUILDING"), (-5.0, "it's -- a 'join', select (select 1)"), (None, None), (float("nan"), ""), (-1.0, None), (-0.5, "two\nlines\r")] * 30)] + [(-7, -1.0, "MACHINERY"), (None, 1.0, "BUILDING")]


def customers(spark):
    return spark.createDataFrame(CUSTOMERS, "c_custkey long, c_acctbal double, c_mktsegment string")


def reads_customer(df):
    return any("customer" in p for p in df.inputFiles())


def test_bank_classes_of_what_customers_ask(spark):
    got, df = same_as_sql(spark, "bank_classes", {"customer": customers(spark)})
    stratum = {r["sample_id"]: r["stratum"] for r in tables.bank_rows()}
    assert len(got) == len(CUSTOMERS) - 1 and all(r.stratum == stratum[r.sample_id] for r in got)
    assert reads_customer(df)


def test_structure_of_what_customers_ask(spark):
    got, df = same_as_sql(spark, "s1_structure", {"customer": customers(spark)})
    owes = {k for k, b, _ in CUSTOMERS if b is not None and b < 0}
    ends = {k for k, _, q in workloads._all_texts() if q.rsplit(" ", 2)[-2] == "limit"}
    assert len(got) == len(CUSTOMERS) - 1 and reads_customer(df)
    assert all(r["limit"] == (r.c_custkey in owes or r.sample_id in ends) for r in got)


def test_plan_steps_of_what_customers_ask(spark, sf):
    given = {t: tables.read_table(spark, sf, t) for t in tables.TABLES if t != "customer"}
    got, df = same_as_sql(spark, "m1_plan_steps", given | {"customer": customers(spark)})
    assert len(got) == len(CUSTOMERS) - 1 and reads_customer(df) and {r.limits for r in got} == {0, 1}


def test_lint_of_what_customers_ask(spark, sf):
    given = {t: tables.read_table(spark, sf, t) for t in tables.TABLES if t != "customer"}
    named = customers(spark).selectExpr("*", "'x' as c_name", "1 as c_nationkey")
    got, df = same_as_sql(spark, "m3_lint", given | {"customer": named})
    assert len(got) == len(CUSTOMERS) - 1 and reads_customer(df) and all(r.wrong == 0 and r.agrees for r in got)


def test_refusals_of_what_customers_send(spark, sf):
    given = {t: tables.read_table(spark, sf, t) for t in tables.TABLES if t != "customer"}
    got, df = same_as_sql(spark, "e1_refused", given | {"customer": customers(spark)})
    assert len(got) == len(CUSTOMERS) - 1 and reads_customer(df) and all(r.condition for r in got)


def test_json_bank_keeps_what_customers_ask(spark):
    got, df = same_as_sql(spark, "src_json_bank", {"customer": customers(spark)})
    assert len({r.sample_id for r in got}) == len(CUSTOMERS) - 1 and {r.sample_id.split("|")[1] for r in got} == {str(k) for k, _, _ in CUSTOMERS[:-1]}


def test_constructs_counted_of_what_customers_ask(spark, tmp_path):
    customers(spark).write.parquet(f"{tmp_path}/customer.parquet")
    df = workloads.udf_pandas(spark, str(tmp_path))
    asked = {r.c_custkey: r.sql for r in workloads._asked(spark, str(tmp_path), workloads._all_texts()).collect()}
    got = {r.c_custkey: r.n for r in df.collect()}
    assert reads_customer(df) and set(got) == {k for k, _, _ in CUSTOMERS[:-1]}
    assert got == {k: len(complexity.structure(q)) for k, q in asked.items()}
    odd = spark.createDataFrame([("select 1 limit 1",), (None,), ("",), ("select 1 limit 1",)], "q string").select(relational.keyword_count("q").alias("n"))
    assert [r.n for r in odd.collect()] == [1, 0, 0, 1]
