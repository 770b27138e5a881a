"""Personal data: high-recall generators, boosted trees, calibrated thresholds.

Base spans (email, ip, card, phone) follow fixed patterns and checks. Beside
them generators propose overlapping candidates in looser and stricter formats;
gradient-boosted trees score format and context features of each, and a
candidate is redacted above a threshold calibrated for precision on held-out
labelled rows. The labelled rows are a seeded set of ``TRAINING_ROWS`` rendered
texts (true formats and look-alikes such as dates, versions, order numbers and
keys); the trees become one SQL expression. The path over documents uses
built-in functions only, touches each text once, and has no shuffle.

Positions come from the lengths of what a pattern matches and what lies
between (code points). The ``\\G``-or-lookbehind prefix keeps leftmost
non-overlapping matching and makes it linear in long runs.

Defined results: null text is the empty text; empty texts have no spans; equal
rows give equal spans; an empty table gives no rows; other columns pass in
``row``.
"""

from __future__ import annotations

import functools
import random

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import let

KINDS = ("email", "ip", "card", "phone")
#: Fixed patterns; possessive forms match the same, since what follows is never inside the class before it.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++){3}",
    "card": r"(?:\G|(?<![0-9]))[0-9]++(?:[\x20-][0-9]++)*+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
GUARD = {"email": "@", "ip": r"[0-9]\.[0-9]", "card": r"[0-9](?:[ -]?[0-9]){12}", "phone": "+"}
OCTET = r"0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"
#: Generators: name, kind, pattern, cheap guard.
GENERATORS = (
    ("run", "card", r"(?<![0-9])[0-9]{13,19}(?![0-9])", r"[0-9]{13}"),
    ("grouped", "card", r"(?<![0-9])(?:[0-9]{4}[ -][0-9]{4}[ -][0-9]{4}[ -][0-9]{4}|[0-9]{4}[ -][0-9]{6}[ -][0-9]{5})(?![0-9])", r"[0-9][ -][0-9]{4}"),
    ("abroad", "phone", r"\+[0-9]{1,3}[ .-]?(?:\([0-9]{2,4}\)|[0-9]{2,4})[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}(?![0-9])", r"\+[0-9]"),
    ("national", "phone", r"(?<![0-9+(])(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9])", r"[0-9]{3}[ .-][0-9]{4}"),
    ("spelled", "email", r"(?i)(?<![a-z0-9._%+-])[a-z0-9._%+-]{2,64} ?[\[(] ?at ?[\])] ?[a-z0-9-]{1,63}(?: ?(?:[\[(] ?dot ?[\])]|\.) ?[a-z0-9-]{2,63}){1,4}", r"(?i)[\[(] ?at ?[\])]"),
    ("inner", "ip", r"(?<![0-9.])[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}(?![0-9]|\.[0-9])", r"[0-9]\.[0-9]{1,3}\.[0-9]"),
)
HINTS = r"(?i)(?:phone|tel|call|mobile|fax|dial|card|visa|credit|pay|mail|contact|reach|ip|host|server|address|client)\W*(?:\w+\W+)?$"
COUNTER = r"(?i)(?:version|release|order|invoice|isbn|serial|key|token|id|no|number|build|date|since|hash)\W*$"
TRAINING_ROWS = 1_600
FEATURES = ("generator", "n_digits", "luhn", "plus", "parens", "seps", "prev", "next", "hint", "counter", "octets", "spread")


def digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def luhn(number: Column) -> Column:
    """Whether a string of digits passes Luhn's check."""
    ds = F.transform(F.split(F.reverse(number), ""), lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise((d.cast("int") * 2).cast("int") - F.when(d.cast("int") > 4, 9).otherwise(0)))
    return F.coalesce(F.aggregate(ds, F.lit(0), lambda a, d: a + F.coalesce(d, F.lit(0))) % 10 == 0, F.lit(False))


#: Matches folded at a time: what a fold adds to is copied each time, so it has to stay short.
FOLD = 256


def folded(items: Column, kind: str, first: Column, step, after) -> Column:
    """``items`` (an array) folded in chunks: an array of ``kind`` of what ``step`` puts out.

    ``step(state, item)`` gives (new state, value); ``first`` is the state before all items, and
    ``after(state, chunk)`` the state after a whole chunk, without its values. The work is
    that of one pass, however many items a text has."""
    chunk = lambda c: F.slice(items, c * FOLD + 1, FOLD)

    def started(acc: Column, c: Column) -> Column:
        return F.struct(after(acc["at"], chunk(c)).alias("at"), F.array_append(acc["all"], acc["at"]).alias("all"))

    def inner(state: Column, c: Column) -> Column:
        def one(acc: Column, item: Column) -> Column:
            new, value = step(acc["at"], item)
            return F.struct(new.alias("at"), F.array_append(acc["out"], value).alias("out"))

        return F.aggregate(chunk(c), F.struct(state.alias("at"), F.array().cast(kind).alias("out")), one, lambda acc: acc["out"])

    chunks = F.sequence(F.lit(0), F.floor((F.greatest(F.size(items), F.lit(1)) - 1) / FOLD).cast("int"))
    states = lambda cs: F.aggregate(cs, F.struct(first.alias("at"), F.array().cast("array<int>").alias("all")), started, lambda acc: acc["all"])
    return F.flatten(let(chunks, lambda cs: let(states(cs), lambda s: F.transform(cs, lambda c: inner(F.get(s, c), c)))))


def matches(text: Column, pattern: str, present: Column) -> Column:
    """Array of (start, end, value, before, after) of all matches, by code point."""
    kind = "array<struct<start:int,end:int,value:string,before:string,after:string>>"
    both = F.struct(F.split(text, pattern, -1).alias("gaps"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits"))

    def placed(x: Column) -> Column:
        items = F.transform(x["hits"], lambda hit, i: F.struct(hit.alias("hit"), F.get(x["gaps"], i).alias("gap"), F.left(F.get(x["gaps"], i + 1), F.lit(8)).alias("next")))

        def step(at: Column, m: Column) -> tuple[Column, Column]:
            start = at + F.length(m["gap"])
            end = start + F.length(m["hit"])
            return end, F.struct(start.alias("start"), end.alias("end"), m["hit"].alias("value"), F.right(m["gap"], F.lit(32)).alias("before"), m["next"].alias("after"))

        def after(at: Column, chunk: Column) -> Column:
            return F.aggregate(chunk, at, lambda n, m: n + F.length(m["gap"]) + F.length(m["hit"]))

        return let(items, lambda z: folded(z, kind, F.lit(0), step, after))

    return F.when(present, let(both, placed)).otherwise(F.array().cast(kind))


def base_spans(text: Column) -> dict[str, Column]:
    """Per kind the matches that pass the kind's check."""
    size = lambda m: F.length(digits(m["value"]))
    passes = {
        "email": lambda m: F.lit(True),
        "ip": lambda m: F.rlike(m["value"], F.lit(rf"^{OCTET}(?:\.{OCTET}){{3}}$")),
        "card": lambda m: size(m).between(13, 19) & luhn(digits(m["value"])),
        "phone": lambda m: size(m).between(9, 15),
    }
    present = lambda k: F.contains(text, F.lit(GUARD[k])) if k in ("email", "phone") else F.rlike(text, F.lit(GUARD[k]))
    return {k: F.filter(matches(text, BASE[k], present(k)), passes[k]) for k in KINDS}


def features(m: Column, generator: int) -> Column:
    v, before, after = m["value"], m["before"], m["after"]
    edge = lambda c: F.when(F.length(c) == 0, 0).when(F.rlike(c, F.lit(r"^\s$")), 0).when(F.rlike(c, F.lit(r"^\p{L}$")), 1).when(F.rlike(c, F.lit("^[0-9]$")), 2).when(F.rlike(c, F.lit(r"^[_=/#$\\]$")), 4).otherwise(3)
    d = digits(v)
    yes = lambda c: F.when(c, 1).otherwise(0)
    cols = {
        "generator": F.lit(generator),
        "n_digits": F.length(d),
        "luhn": yes(F.length(d).between(13, 19) & luhn(d)),
        "plus": yes(F.startswith(v, F.lit("+"))),
        "parens": yes(F.contains(v, F.lit("("))),
        "seps": F.length(F.regexp_replace(v, r"[^ .\-]", "")),
        "prev": edge(F.right(before, F.lit(1))),
        "next": edge(F.left(after, F.lit(1))),
        "hint": yes(F.rlike(before, F.lit(HINTS))),
        "counter": yes(F.rlike(before, F.lit(COUNTER))),
        "octets": yes(F.rlike(v, F.lit(rf"^{OCTET}(?:\.{OCTET}){{3}}$"))),
        "spread": F.size(F.array_distinct(F.split(d, ""))),
    }
    return F.struct(*[cols[k].cast("double").alias(k) for k in FEATURES])


def candidates(text: Column) -> Column:
    """Array of (kind, start, end, f) that all generators propose; they may overlap."""
    def item(g: int, kind: str):
        return lambda m: F.struct(F.lit(kind).alias("kind"), m["start"].alias("start"), m["end"].alias("end"), features(m, g).alias("f"))

    found = [F.transform(matches(text, pattern, F.rlike(text, F.lit(guard))), item(g, kind)) for g, (_, kind, pattern, guard) in enumerate(GENERATORS)]
    return F.concat(*found)


# --- labelled rows and the trees ------------------------------------------------------------


def labelled_rows(seed: int = 11, rows: int = TRAINING_ROWS) -> list[tuple[int, str, str, int]]:
    """(row, text, the planted string, whether it is personal data), half of each."""
    rnd = random.Random(seed)
    n = lambda k: "".join(rnd.choice("0123456789") for _ in range(k))
    word = lambda: "".join(rnd.choice("aeioulnrst") for _ in range(rnd.randint(2, 9)))

    def card(groups: bool) -> str:
        body = rnd.choice("3456") + n(14)
        check = next(c for c in "0123456789" if luhn_ok(body + c))
        x = body + check
        return rnd.choice(" -").join(x[i : i + 4] for i in range(0, 16, 4)) if groups else x

    def no_card() -> str:
        x = n(rnd.choice((13, 14, 15, 16, 16, 16, 18)))
        return x if not luhn_ok(x) else no_card()

    ip = lambda: ".".join(str(rnd.randint(1, 254)) for _ in range(4))
    area = lambda: rnd.choice("23456789") + n(2)
    true = [lambda: card(False), lambda: f"+{rnd.randint(1, 99)} {n(3)} {n(3)} {n(4)} {card(False)}"[-16:], lambda: card(True), lambda: f"+{rnd.randint(1, 99)} ({area()}) {n(3)}-{n(4)}", lambda: f"+{rnd.randint(1, 99)} {area()} {n(3)} {n(4)}", lambda: f"({area()}) {n(3)}-{n(4)}", lambda: f"{area()}-{n(3)}-{n(4)}", lambda: f"{word()}.{word()} (at) {word()}.com", lambda: f"{word()}[at]{word()} [dot] org", ip]
    false = [no_card, no_card, lambda: f"{rnd.randint(1, 9)}.{rnd.randint(300, 999)}.{n(1)}.{n(2)}", lambda: f"{n(4)} {n(4)} {n(4)} {n(4)}", lambda: f"{n(3)}.{n(3)}.{n(4)}", lambda: f"{n(3)} {n(3)} {n(4)}", lambda: f"{word()} (at) {word()} .{word()}", ip, lambda: n(3) + "-" + n(3) + "-" + n(4)]
    warm = ("call ", "phone: ", "tel ", "card ", "pay with ", "contact ", "mail ", "host ", "client ip ", "reach us on ")
    cold = ("version ", "order ", "invoice no ", "isbn ", "serial ", "build ", "key=", "token = \"", "id", "a", "x/", "hash ", "since ")
    out = []
    for i in range(rows):
        good = i % 2 == 0
        x = rnd.choice(true if good else false)()
        around = rnd.choice(warm) if good and rnd.random() < 0.5 else rnd.choice(cold) if not good else ""
        end = rnd.choice((" ", ", ", ".", "\n")) if good else rnd.choice((" ", "", "ab", "_1", "/2", ".", "."))
        out.append((i, f"{word()} {word()} {around}{x}{end}{word() if end != '' else 'f' + word()} {word()}", x, int(good)))
    return out


def luhn_ok(x: str) -> bool:
    return sum(sum(divmod(2 * int(d), 10)) if i % 2 else int(d) for i, d in enumerate(reversed(x))) % 10 == 0


def boost(x: np.ndarray, y: np.ndarray, rounds: int = 40, rate: float = 0.3, least: int = 8) -> tuple[float, list]:
    """Gradient boosting with depth-two trees and logistic loss: (start, trees). A tree is
    (feature, threshold, left, right); a side is such a tuple or a leaf's value."""
    start = float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
    score, trees = np.full(len(y), start), []

    def grow(rows: np.ndarray, g: np.ndarray, h: np.ndarray, depth: int):
        leaf = float(rate * g[rows].sum() / (h[rows].sum() + 1.0))
        best = (1e-6, None)
        if depth:
            whole = g[rows].sum() ** 2 / (h[rows].sum() + 1.0)
            for f in range(x.shape[1]):
                values = np.unique(x[rows, f])
                for t in (values[1:] + values[:-1]) / 2:
                    left = rows & (x[:, f] <= t)
                    right = rows & ~left
                    if left.sum() >= least and right.sum() >= least:
                        gain = g[left].sum() ** 2 / (h[left].sum() + 1.0) + g[right].sum() ** 2 / (h[right].sum() + 1.0) - whole
                        if gain > best[0]:
                            best = (gain, (f, float(t), left, right))
        if best[1] is None:
            return leaf
        f, t, left, right = best[1]
        return f, t, grow(left, g, h, depth - 1), grow(right, g, h, depth - 1)

    for _ in range(rounds):
        p = 1 / (1 + np.exp(-score))
        tree = grow(np.ones(len(y), bool), y - p, p * (1 - p), 3)
        trees.append(tree)
        score = score + apply_tree(tree, x)
    return start, trees


def apply_tree(tree, x: np.ndarray) -> np.ndarray:
    if not isinstance(tree, tuple):
        return np.full(len(x), tree)
    f, t, left, right = tree
    return np.where(x[:, f] <= t, apply_tree(left, x), apply_tree(right, x))


def tree_column(tree, f: Column) -> Column:
    if not isinstance(tree, tuple):
        return F.lit(tree)
    i, t, left, right = tree
    return F.when(f[FEATURES[i]] <= t, tree_column(left, f)).otherwise(tree_column(right, f))


_models: dict[tuple, tuple] = {}


def fit(spark: SparkSession, seed: int = 11, precision: float = 0.98) -> tuple[float, list, dict[str, float]]:
    """(start, trees, threshold by kind), from the labelled rows; remembered by its parameters.

    The last quarter of the rows isn't fitted: a kind's threshold is the lowest score
    from which at least ``precision`` of those candidates are true, and never under 0.
    """
    if (seed, precision) in _models:
        return _models[seed, precision]
    data = spark.createDataFrame(labelled_rows(seed), "row int, text string, planted string, good int")
    got = data.select("row", "good", F.instr("text", F.col("planted")).alias("at"), F.length("planted").alias("n"), F.explode(candidates(F.col("text"))).alias("c"))
    hit = (F.col("good") == 1) & (F.col("c.end") - F.col("c.start") >= F.col("n") - 5)
    rows = got.select("row", hit.cast("int").alias("y"), "c.kind", "c.f.*").orderBy("row", "kind", *FEATURES).collect()
    x, y = np.array([[r[k] for k in FEATURES] for r in rows]), np.array([r["y"] for r in rows], float)
    kinds, held = np.array([r["kind"] for r in rows]), np.array([r["row"] % 8 >= 6 for r in rows])
    start, trees = boost(x[~held], y[~held])
    score = start + functools.reduce(np.add, [apply_tree(t, x) for t in trees])
    limits = {}
    for k in KINDS:
        s, t = score[held & (kinds == k)], y[held & (kinds == k)]
        fine = [v for v in np.unique(s) if t[s >= v].mean() >= precision]
        limits[k] = max(0.0, float(min(fine, default=np.inf)))
    _models[seed, precision] = start, trees, limits
    return _models[seed, precision]


def find(docs: DataFrame, seed: int = 11, columns: list[str] | None = None) -> DataFrame:
    """row, base (array of kind, start, end) and spans (base and added ones), both in the
    order of KINDS, then start. An added span inside another of its kind is left out."""
    start, trees, limits = fit(docs.sparkSession, seed)
    text = F.coalesce(F.col("text"), F.lit(""))
    out = docs.select(F.struct(*(columns or docs.columns)).alias("row"), F.struct(*[c.alias(k) for k, c in base_spans(text).items()]).alias("base"), candidates(text).alias("proposed"))

    def sure(c: Column) -> Column:
        score = functools.reduce(lambda a, b: a + b, [tree_column(t, c["f"]) for t in trees], F.lit(start))
        limit = functools.reduce(lambda a, k: F.when(c["kind"] == k, limits[k] if limits[k] != float("inf") else 1e9).otherwise(a), KINDS, F.lit(1e9))
        return score >= limit

    spans = "array<struct<kind:string,start:int,end:int>>"
    plain = lambda k: F.transform(F.col(f"base.{k}"), lambda m: F.struct(F.lit(k).alias("kind"), m["start"].alias("start"), m["end"].alias("end")))

    def merged(k: str) -> Column:
        ordered = F.sort_array(F.concat(F.transform(F.col(f"base.{k}"), lambda m: F.struct(m["start"].alias("start"), (-m["end"]).alias("back"), F.lit(0).alias("added"))), F.transform(F.filter("added", lambda c: c["kind"] == k), lambda c: F.struct(c["start"].alias("start"), (-c["end"]).alias("back"), F.lit(1).alias("added")))))

        def step(far: Column, m: Column) -> tuple[Column, Column]:
            inside = (m["added"] == 1) & (-m["back"] <= far)
            item = F.when(~inside, F.struct(F.lit(k).alias("kind"), m["start"].alias("start"), (-m["back"]).alias("end")))
            return F.greatest(far, -m["back"]), item

        def after(far: Column, chunk: Column) -> Column:
            return F.aggregate(chunk, far, lambda n, m: F.greatest(n, -m["back"]))

        return F.filter(let(ordered, lambda z: folded(z, spans, F.lit(0), step, after)), lambda s: s.isNotNull())

    out = out.select("row", "base", F.filter("proposed", sure).alias("added"))
    return out.select("row", F.concat(*[plain(k) for k in KINDS]).cast(spans).alias("base"), F.concat(*[F.when(F.size("added") == 0, plain(k)).otherwise(merged(k)) for k in KINDS]).cast(spans).alias("spans"))


def redact(text: Column, spans: Column) -> Column:
    """The text with each span (overlaps as one, named by the first) put as [KIND]."""
    ordered = F.sort_array(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))

    def step(far: Column, s: Column) -> tuple[Column, Column]:
        cut = F.struct(far.alias("from"), s["start"].alias("to"), s["kind"].alias("kind"))
        return F.greatest(far, s["end"]), F.when(s["start"] >= far, cut)

    def after(far: Column, chunk: Column) -> Column:
        return F.aggregate(chunk, far, lambda n, s: F.greatest(n, s["end"]))

    def written(cuts: Column) -> Column:
        # what stands between cuts is read from a chunk's own stretch of the text, not from its start
        def stretch(c: Column) -> Column:
            def pieces(part: Column) -> Column:
                base = F.element_at(part, 1)["from"]
                whole = F.substr(text, base + 1, F.element_at(part, -1)["to"] - base)
                put = lambda w: F.array_join(F.transform(part, lambda p: F.concat(F.substr(w, p["from"] - base + 1, p["to"] - p["from"]), F.lit("["), F.upper(p["kind"]), F.lit("]"))), "")
                return let(whole, put)

            return let(F.slice(cuts, c * FOLD + 1, FOLD), pieces)

        chunks = F.sequence(F.lit(0), F.floor((F.size(cuts) - 1) / FOLD).cast("int"))
        return F.concat(F.array_join(F.transform(chunks, stretch), ""), F.substr(text, F.array_max(F.transform(spans, lambda s: s["end"])) + 1))

    cuts = let(ordered, lambda z: folded(z, "array<struct<from:int,to:int,kind:string>>", F.lit(0), step, after))
    return F.when(F.size(spans) == 0, text).otherwise(let(F.filter(cuts, lambda c: c.isNotNull()), written))
