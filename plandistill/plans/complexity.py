"""Structure of a query: complexity class and constructs, from a lexer that runs on executors and,
exactly, from Catalyst's parsed plan on the driver."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, StringType

CLASSES = ("single", "sub", "joinset", "joinset_sub")
CONSTRUCTS = ("join", "group_by", "order_by", "set_op", "subquery", "aggregate", "having", "distinct", "limit", "case", "window", "cte")
AGGREGATES = frozenset(("count", "sum", "avg", "min", "max"))
#: Words that end a from clause at their depth.
_ENDS_FROM = frozenset(("where", "group", "having", "order", "limit", "union", "intersect", "except", "window", "select", "offset"))
_TOKEN = re.compile(r"'(?:[^']|'')*'|--[^\n]*|/\*.*?\*/|`[^`]*`|\"[^\"]*\"|\w+|[^\s\w]", re.S)


def words(sql: str) -> list[str]:
    """Words (in lower case), strings, quoted names and signs of a query, without its comments."""
    return [t.lower() if re.match(r"\w", t) else t for t in _TOKEN.findall(sql) if not t.startswith(("--", "/*"))]


def structure(sql: str) -> list[str]:
    """The constructs of a query, in the order of ``CONSTRUCTS``: one pass over its words with a
    stack of brackets. Strings, comments and quoted names are no words; a comma in a from
    clause joins; an order inside a window isn't the query's."""
    said = words(sql)
    found: set[str] = set()
    stack = [{"window": False, "from": False}]
    for i, w in enumerate(said):
        before, after = said[i - 1] if i else "", said[i + 1] if i + 1 < len(said) else ""
        here = stack[-1]
        if w == "(":
            if after in ("select", "with"):
                found.add("subquery")
            named = before == "as" and i > 2 and said[i - 3] in ("window", ",") and "window" in said[:i] and after in ("partition", "order", "rows", "range", ")")
            stack.append({"window": before == "over" or named, "from": False})
        elif w == ")":
            if len(stack) > 1:
                stack.pop()
        elif w == "from" and not (before == "distinct" and said[i - 2] in ("is", "not")):
            here["from"] = True
        elif w == "," and here["from"] or w == "join":
            found.add("join")
        elif w in ("union", "intersect", "except"):
            found.add("set_op")
        elif w == "with" and (i == 0 or before == "("):
            found |= {"cte", "subquery"}
        elif w == "by" and before == "group":
            found.add("group_by")
        elif w == "by" and before == "order" and not here["window"]:
            found.add("order_by")
        elif w == "distinct" and after != "from":
            found.add("distinct")
        elif w in ("having", "limit", "case"):
            found.add(w)
        elif w == "over" and before == ")":
            found.add("window")
        elif w in AGGREGATES and after == "(":
            found.add("aggregate")
        if w in _ENDS_FROM:
            here["from"] = False
    return [c for c in CONSTRUCTS if c in found]


def _class(found: list[str]) -> str:
    return CLASSES[("subquery" in found) + 2 * ("join" in found or "set_op" in found)]


def by_text(sql: pd.Series, f) -> pd.Series:
    """``f`` of each text, worked out once for each different one of a batch; null stays null."""
    known = {x: f(x) for x in sql.dropna().unique()}
    return sql.map(known.get, na_action="ignore")


@F.pandas_udf(ArrayType(StringType()))
def _constructs(sql: pd.Series) -> pd.Series:
    return by_text(sql, structure)


@F.pandas_udf(StringType())
def _complexity(sql: pd.Series) -> pd.Series:
    return by_text(sql, lambda x: _class(structure(x)))


def complexity(sql: Column) -> Column:
    """single, sub, joinset or joinset_sub; null text gives null."""
    return _complexity(sql)


def constructs(sql: Column) -> Column:
    """The constructs of a query; null text gives null."""
    return _constructs(sql)


def exact_complexity(spark: SparkSession, sql: str) -> str:
    """From the parsed plan: joins and set operations, and subqueries wherever they stand."""
    from .ir import _items

    linked = nested = False

    def walk(node) -> None:
        nonlocal linked, nested
        name = node.nodeName()
        linked |= name in ("Join", "LateralJoin", "Union", "Intersect", "Except")
        if name == "UnresolvedWith":
            nested = True
            for pair in _items(node.cteRelations()):
                walk(pair._2())
        if name == "SubqueryAlias" and node.child().nodeName() != "UnresolvedRelation":
            nested = True
        subs = _items(node.subqueries())
        nested |= bool(subs)
        for x in [*_items(node.children()), *subs]:
            walk(x)

    walk(spark._jsparkSession.sessionState().sqlParser().parsePlan(sql))
    return CLASSES[nested + 2 * linked]


def normalised(sql: str) -> str:
    return re.sub(r"\s+", " ", sql.strip().rstrip(";")).lower()
