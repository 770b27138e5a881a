"""Safe execution of predicted SQL, result digests, and error classes.

A digest is one row: counts and order-blind sums of two hashes of the rows, by
position and not by name; only digests leave the executors.
"""

from __future__ import annotations

import re
import threading
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.errors import PySparkException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import DATABASES, register

#: Clause keywords in the order in which they may stand.
CLAUSES = ("select", "from", "where", "group", "having", "order", "limit")
KEYWORDS = (*CLAUSES, "by", "join", "on", "union", "intersect", "except", "distinct", "as", "and", "or", "in", "exists", "case", "when", "then", "else", "end")
ORDERED_CAP = 1_000_000
#: Plan nodes, functions and expressions that a predicted query may use; anything else is refused
#: before it is analysed, wherever in the tree it stands.
NODES = frozenset("Project Aggregate Filter Sort GlobalLimit LocalLimit Offset Distinct Union Intersect Except UnresolvedWith UnresolvedHaving Join LateralJoin UnresolvedInlineTable ResolvedInlineTable LocalRelation OneRowRelation SubqueryAlias UnresolvedSubqueryColumnAliases UnresolvedRelation WithWindowDefinition UnresolvedHint Pivot".split())
FUNCTIONS = frozenset(
    """count sum avg mean min max first last any_value first_value last_value max_by min_by median percentile approx_count_distinct
    stddev stddev_samp stddev_pop variance var_samp var_pop corr bool_and bool_or every some any collect_list collect_set array_agg count_if grouping grouping_id
    row_number rank dense_rank percent_rank cume_dist ntile lag lead nth_value
    abs ceil ceiling floor round sqrt exp ln log log10 log2 pow power mod pmod sign greatest least sin cos tan
    coalesce nullif ifnull nvl nvl2 if isnull isnotnull
    lower upper lcase ucase length char_length character_length len trim ltrim rtrim btrim substring substr left right replace concat concat_ws split split_part instr locate position reverse lpad rpad regexp_replace regexp_extract regexp_like contains startswith endswith like ilike initcap repeat translate md5
    year month day dayofmonth dayofweek dayofyear quarter hour minute second date to_date to_timestamp date_trunc trunc datediff date_add date_sub add_months last_day months_between extract date_part date_format current_date make_date unix_timestamp
    cast int integer bigint double float decimal string boolean size cardinality array array_contains element_at explode get_json_object not and or in between""".split()
)
REFUSED_EXPRESSIONS = frozenset(("ExpressionWithUnresolvedIdentifier", "UnresolvedTableValuedFunction", "CallFunction", "ScalaUDF", "PythonUDF"))


@dataclass(frozen=True)
class Digest:
    status: str  # ok or error
    n_cols: int = -1
    n_rows: int = -1
    bag: tuple = ()
    set: tuple = ()
    ordered: tuple = ()
    error: str = ""
    leaf: str = ""


def _number(c: Column, kind: str, digits: int | None) -> Column:
    """A number as text. Numbers are equal if they are the same double, whatever type holds them;
    what no double holds keeps its own digits. Floating columns are taken to ``digits``
    significant digits, as their sums depend on the order of rows; None compares every bit."""
    near = c.cast("double") + F.lit(0.0)  # -0.0 becomes 0.0
    if kind in ("float", "double"):
        sound = ~F.isnan(near) & (F.abs(near) < float("inf"))
        short = near if digits is None else F.when(sound, F.format_string(f"%.{digits - 1}e", near).cast("double")).otherwise(near)
        return short.cast("string")
    if kind.startswith("decimal"):
        return F.when(near.try_cast(kind) == c, near.cast("string")).otherwise(F.regexp_replace(c.cast("string"), r"\.?0+$", ""))
    return F.when(c.between(-(1 << 53), 1 << 53), near.cast("string")).otherwise(c.cast("string"))


def canonical(df: DataFrame, digits: int | None = 12) -> DataFrame:
    """Columns by position in comparable form: numbers by value, the rest as text."""
    out = []
    for i, (_, kind) in enumerate(df.dtypes):
        c = F.col(f"c{i}")
        if re.match(r"(tinyint|smallint|int|bigint|float|double|decimal)\b", kind):
            c = _number(c, kind, digits)
        elif not re.match("(array|map|struct|binary)", kind):
            c = c.cast("string")
        else:
            c = F.to_json(F.struct(c))
        out.append(F.coalesce(F.concat(F.lit("v"), c), F.lit("n")).alias(f"c{i}"))
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))]).select(*out)


def positions(df: DataFrame, digits: int | None = 12) -> DataFrame:
    """One row, of a query's rows in the order it gives: two sums over hashes of position and
    row. One task numbers the rows, so results have to be capped."""
    keyed = canonical(df, digits)
    at = F.row_number().over(Window.orderBy("at"))
    placed = keyed.withColumn("at", F.monotonically_increasing_id()).withColumn("at", at)
    total = lambda seed: F.coalesce(F.sum(F.xxhash64(F.lit(seed), "at", *keyed.columns).cast("decimal(20,0)")), F.lit(0)).cast("decimal(38,0)")
    return placed.agg(total(3).alias("ordered_a"), total(4).alias("ordered_b"))


def digest(df: DataFrame, digits: int | None = 12) -> DataFrame:
    """One row: n_cols, n_rows, two sums for the bag and two for the set of rows."""
    keyed = canonical(df, digits)
    row = keyed.select(F.xxhash64(F.lit(1), *keyed.columns).alias("a"), F.xxhash64(F.lit(2), *keyed.columns).alias("b"))
    total = lambda c: F.coalesce(F.sum(F.col(c).cast("decimal(20,0)")), F.lit(0)).cast("decimal(38,0)")
    per = row.groupBy("a", "b").agg(F.count("*").alias("k"))
    times = lambda c: F.coalesce(F.sum(F.col(c).cast("decimal(20,0)") * F.col("k")), F.lit(0)).cast("decimal(38,0)")
    return per.agg(F.lit(len(df.columns)).alias("n_cols"), F.coalesce(F.sum("k"), F.lit(0)).alias("n_rows"), times("a").alias("bag_a"), times("b").alias("bag_b"), total("a").alias("set_a"), total("b").alias("set_b"), F.count("*").alias("n_distinct"))


def database_session(spark: SparkSession, sf_dir: str, db_id: str) -> SparkSession:
    """A private session with the views of one database, judging keywords strictly."""
    own = spark.newSession()
    own.conf.set("spark.sql.ansi.enforceReservedKeywords", "true")
    register(own, sf_dir, DATABASES[db_id])
    return own


def _distance(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, last = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    return row[-1]


def syntax_leaf(condition: str, params: dict, sql: str) -> str:
    """The leaf of a query that didn't run."""
    if condition.startswith(("UNRESOLVED_COLUMN", "MISSING_ATTRIBUTES", "UNRESOLVED_FIELD")):
        return "no such column"
    if condition == "TABLE_OR_VIEW_NOT_FOUND":
        return "no such table"
    if condition == "PARSE_SYNTAX_ERROR":
        token, hint = params.get("error", "").strip("'").lower(), params.get("hint", "")
        words = re.findall(r"[a-z_]+|[()]", re.sub(r"'[^']*'", "", sql.lower()))
        first = words[0] if words else ""
        if first not in KEYWORDS and first != "with" and any(_distance(first, k) <= 2 for k in ("select", "with")):
            return "keyword"
        if sql.count("(") != sql.count(")") or "missing ')'" in hint:
            return "clause order"
        if token in CLAUSES or token == "by":
            seen = [w for w in words if w in CLAUSES]
            if words.count(token) > 1 and any(a == b == token for a, b in zip(words, words[1:], strict=False)):
                return "keyword"
            if seen != sorted(seen, key=CLAUSES.index):
                return "clause order"
        if "by" in words and not re.search(r"(group|order|partition)\s+by", sql.lower()):
            return "clause order"
        return "keyword"
    return "other"


def _elements(seq) -> list:
    out, it = [], seq.iterator()
    while it.hasNext():
        out.append(it.next())
    return out


def refusal(session: SparkSession, sql: str, tables: tuple[str, ...] | None = None) -> tuple[str, str] | None:
    """(condition, leaf) if the query may not run, else None; judged on the parsed tree alone.

    Every node, subquery and expression is walked. Relations are names of the database or of
    the query's own common table expressions, never paths or qualified names."""
    found: list[tuple[str, str]] = []

    def expression(e) -> None:
        if e.getClass().getSimpleName() in REFUSED_EXPRESSIONS:
            found.append(("EXPRESSION_NOT_ALLOWED", "other"))
        if e.getClass().getSimpleName() == "UnresolvedFunction":
            parts = [str(x) for x in _elements(e.nameParts())]
            if len(parts) != 1 or parts[0].lower() not in FUNCTIONS:
                found.append(("FUNCTION_NOT_ALLOWED", "other"))
        for x in _elements(e.children()):
            expression(x)

    def walk(node, scope: frozenset[str]) -> None:
        name = node.nodeName()
        if name not in NODES:
            found.append(("NODE_NOT_ALLOWED", "other"))
            return
        if name == "UnresolvedWith":
            for pair in _elements(node.cteRelations()):
                inner = str(pair._1()).lower()
                walk(pair._2(), scope | {inner} if node.allowRecursion() else scope)
                scope = scope | {inner}
        if name == "UnresolvedRelation":
            parts = [str(x).lower() for x in _elements(node.multipartIdentifier())]
            if len(parts) != 1 or (tables is not None and parts[0] not in tables and parts[0] not in scope):
                found.append(("TABLE_OR_VIEW_NOT_FOUND", "no such table"))
        for e in _elements(node.expressions()):
            expression(e)
        for x in [*_elements(node.subqueries()), *_elements(node.children())]:
            walk(x, scope)

    walk(session._jsparkSession.sessionState().sqlParser().parsePlan(sql), frozenset())
    return min(found, key=lambda x: x[0] != "TABLE_OR_VIEW_NOT_FOUND") if found else None


def run_sql(session: SparkSession, sql: str, tables: tuple[str, ...] | None = None, max_rows: int | None = None, seconds: float | None = None, ordered: bool = False, digits: int | None = 12) -> Digest:
    """The digest of a query in a database's session (with row positions if ``ordered``,
    which one task numbers, so at most ``ORDERED_CAP`` rows unless a cap is given). A query that isn't allowed, has more than ``max_rows`` rows or takes more
    than ``seconds`` is an error of leaf other; no result is cut short."""
    max_rows = ORDERED_CAP if ordered and max_rows is None else max_rows
    group, late = f"plandistill-{uuid.uuid4().hex}", threading.Event()
    context = session.sparkContext

    def stop() -> None:
        late.set()
        context.cancelJobGroup(group)

    timer = threading.Timer(seconds, stop) if seconds else None
    try:
        refused = refusal(session, sql, tables)
        if refused:
            return Digest("error", error=refused[0], leaf=refused[1])
        if timer:
            context.setJobGroup(group, "predicted query", interruptOnCancel=True)
            timer.start()
        df = session.sql(sql)
        capped = df if max_rows is None else df.limit(max_rows + 1)
        r = digest(capped, digits).head()
        if max_rows is not None and r.n_rows > max_rows:
            return Digest("error", error="ROW_CAP", leaf="other")
        placed = tuple(positions(df, digits).head()) if ordered else ()
        if late.is_set():
            return Digest("error", error="TIMEOUT", leaf="other")
        return Digest("ok", r.n_cols, r.n_rows, (r.bag_a, r.bag_b, r.n_rows), (r.set_a, r.set_b, r.n_distinct), placed)
    except PySparkException as e:
        if late.is_set():
            return Digest("error", error="TIMEOUT", leaf="other")
        condition = e.getCondition() or "UNKNOWN"
        return Digest("error", error=condition, leaf=syntax_leaf(condition, e.getMessageParameters() or {}, sql))
    except Exception as e:  # the JVM's own errors carry their class in brackets
        if late.is_set():
            return Digest("error", error="TIMEOUT", leaf="other")
        found = re.search(r"\[([A-Z_.]+)\]", str(e))
        condition = found[1] if found else type(e).__name__
        return Digest("error", error=condition, leaf=syntax_leaf(condition, {}, sql))
    finally:
        if timer:
            timer.cancel()
            context.setLocalProperty("spark.jobGroup.id", None)


def run_many(spark: SparkSession, sf_dir: str, asked: list[tuple[str, str]], threads: int = 8, seconds: float | None = None, max_rows: int | None = None, ordered: bool = False) -> dict[tuple[str, str], Digest]:
    """Each different (database, SQL) once, several at a time; digests only come back."""
    sessions = {db: database_session(spark, sf_dir, db) for db in {db for db, _ in asked}}
    todo = sorted(set(asked))
    one = lambda x: run_sql(sessions[x[0]], x[1], DATABASES[x[0]], max_rows, seconds, ordered)
    with ThreadPoolExecutor(threads) as pool:
        return dict(zip(todo, pool.map(one, todo), strict=True))


def same_result(a: Digest, b: Digest, mode: str = "set", strict_arity: bool = True) -> bool:
    if mode not in ("set", "bag", "ordered"):
        raise ValueError(f"unknown mode {mode}")
    if a.status != "ok" or b.status != "ok":
        return False
    if not a.n_rows and not b.n_rows:
        return a.n_cols == b.n_cols or not strict_arity
    if mode == "ordered" and not (a.ordered and b.ordered):
        raise ValueError("a digest without row positions")
    return a.n_cols == b.n_cols and getattr(a, mode) == getattr(b, mode)


def same_rows(a: DataFrame, b: DataFrame, mode: str = "bag") -> bool:
    """Exact comparison: nothing is left either way."""
    if len(a.columns) != len(b.columns):
        return False
    x, y = canonical(a), canonical(b)
    if mode == "set":
        x, y = x.distinct(), y.distinct()
    return x.exceptAll(y).isEmpty() and y.exceptAll(x).isEmpty()


def outcome(predicted: Digest | None, gold: Digest, mode: str = "set") -> tuple[str, str]:
    """(level, leaf): GEN without SQL, SYN if it fails, SEM by shape, SUCC."""
    if predicted is None:
        return "GEN", "no output"
    if predicted.status != "ok":
        return "SYN", predicted.leaf
    if same_result(predicted, gold, mode):
        return "SUCC", "success"
    if not predicted.n_rows and gold.n_rows:
        return "SEM", "empty output"
    cols, rows = predicted.n_cols != gold.n_cols, predicted.n_rows != gold.n_rows
    return "SEM", "row & column mismatch" if cols and rows else "column mismatch" if cols else "row mismatch" if rows else "value mismatch"
