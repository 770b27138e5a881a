"""SQL functions for users: structure, tokens and extraction as plain expressions; traces as a table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from ..plans.complexity import _complexity, _constructs
from ..plans.ir import parse_plan, plan_ir, render_plan


def register_functions(spark: SparkSession) -> None:
    """count_tokens, extract_sql, complexity_of, constructs_of, trace_steps and n_trace_steps in
    the session's SQL. A trace of a SQL text needs Catalyst, which executors don't have: see
    ``plan_trace``."""
    @udtf(returnType="step int, op string, args string, inputs array<int>")
    class TraceSteps:
        def eval(self, text: str):
            for s in parse_plan(text or ""):
                yield s.number, s.op, s.args, s.inputs

    @pandas_udf("int")
    def n_trace_steps(text: pd.Series) -> pd.Series:
        return text.fillna("").str.count(r"(?m)^STEP \d+ ")

    spark.udf.register("complexity_of", _complexity)
    spark.udf.register("constructs_of", _constructs)
    spark.sql(r"""create or replace temporary function extract_sql(raw string) returns string return
        nullif(trim(regexp_extract(raw, '(?s)### SQL\\s*(?:```sql|```)?\\s*((?i:select|with)\\b.*?)\\s*(?:```.*)?$', 1)), '')""")
    spark.udtf.register("trace_steps", TraceSteps)
    spark.udf.register("n_trace_steps", n_trace_steps)
    spark.sql(r"create or replace temporary function count_tokens(t string) returns bigint return regexp_count(coalesce(t, ''), '[A-Za-z0-9_]+|[^A-Za-z0-9_\\s]')")


def plan_trace(spark: SparkSession, sql: str, source: str = "analyzed") -> str:
    """The trace of a query over the session's relations, as text."""
    return render_plan(plan_ir(spark, sql, source))
