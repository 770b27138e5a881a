"""Nearest neighbours by inner product: NN-descent graphs in cells, greedy graph search.

Equal vectors are one node (its smallest id), so a vector that a third of the
rows hold costs one node. Vectors are lifted to one length (one more component),
which makes the largest inner product the nearest one. Nodes fall into cells by
their nearest of at most ``MAX_CELLS`` centroids (k-means on a sample of at most
``FIT_ROWS`` nodes; every node is indexed); a cell with more than ``SHARD`` nodes has
several graphs, dealt by a hash, so no graph outgrows a task. A graph
starts with random links and is improved by joins of
neighbours of neighbours: each round joins the sampled links of every node with
themselves, scores the pairs, and keeps each node's ``DEGREE`` best.

A query searches the graphs of its nearest cells greedily with a beam, in
blocks of ``BLOCK`` queries, and their answers are merged. How many cells that takes is
measured: of at most ``PROBES`` queries the true neighbours are found by brute force, and the
fewest cells that hold ``GOAL`` of them are searched by all. On vectors with
structure that is a few cells at any size; on vectors without any (all directions
alike) it comes to most cells, and the work grows with them.

``SAMPLE``, ``DEGREE`` and ``BEAM`` trade time for recall.

Defined results: null or zero vectors, vectors with null, infinite or NaN
components and vectors of another length than most take no part; rows without
id neither; an id that occurs twice stands for each of its rows; fewer
candidates than ``top`` give fewer rows; an empty table gives no rows; other
columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import drop, park, sliced

MAX_CELLS, FIT_ROWS, PROBES, GOAL = 4_096, 1 << 17, 256, 0.98
SHARD, DEGREE, SAMPLE, ROUNDS, BEAM, WIDTH, BLOCK, ENTRIES = 16_384, 32, 8, 5, 320, 8, 4_096, 64


def usable(vectors: DataFrame, id_col: str = "vec_id", column: str = "embedding") -> DataFrame:
    """vec_id and x (array of double) of the rows that take part."""
    v = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(column).cast("array<double>").alias("x"))
    sound = F.forall("x", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists("x", lambda c: c != 0)
    v = v.where(F.col("vec_id").isNotNull() & F.col("x").isNotNull()).where(F.coalesce(sound, F.lit(False)))
    sizes = v.groupBy(F.size("x").alias("n")).count().orderBy(F.desc("count"), "n").head()
    return v.where(F.size("x") == (sizes["n"] if sizes else 0))


def _matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if isinstance(column, pa.ChunkedArray):
        column = column.chunk(0)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.empty((0, 1))


def lifted(x: np.ndarray, longest: float) -> np.ndarray:
    """Unit vectors whose inner products rank as distances of the lifted originals do."""
    x = x / longest
    more = np.sqrt(np.maximum(0.0, 1.0 - np.einsum("ij,ij->i", x, x)))
    return np.concatenate([x, more[:, None]], axis=1).astype(np.float32)


def _best(u: np.ndarray, v: np.ndarray, x: np.ndarray, keep: int) -> tuple[np.ndarray, np.ndarray]:
    """The ``keep`` nearest distinct partners of each u."""
    n = len(x)
    key = np.unique(u.astype(np.int64) * n + v)
    u, v = (key // n).astype(np.int32), (key % n).astype(np.int32)
    u, v = u[u != v], v[u != v]
    score = np.empty(len(u), np.float32)
    for i in range(0, len(u), 1 << 17):
        s = slice(i, i + (1 << 17))
        score[s] = np.einsum("ij,ij->i", x[u[s]], x[v[s]])
    order = np.lexsort((v, -score, u))
    u, v = u[order], v[order]
    rank = np.arange(len(u)) - np.searchsorted(u, u)
    return u[rank < keep], v[rank < keep]


def build_graph(nodes: DataFrame, longest: float, rounds: int = ROUNDS, seed: int = 3) -> DataFrame:
    """shard, u, v: links of nodes (shard, i, size, x) by NN-descent."""
    seeds = nodes.select("shard", F.col("i").alias("u"), "size", F.explode(F.sequence(F.lit(1), F.lit(DEGREE))).alias("k"))
    links = seeds.select("shard", "u", F.pmod(F.xxhash64(F.lit(seed), "shard", "u", "k"), F.col("size")).cast("int").alias("v"), F.lit(True).alias("new")).where("u <> v")
    links = park(links.distinct(), "links")

    def improve(pairs: pa.Table, points: pa.Table) -> pa.Table:
        order = np.argsort(points.column("i").to_numpy())
        x = lifted(_matrix(points.column("x"))[order], longest)
        u, v, old = (pairs.column(c).to_numpy() for c in ("u", "v", "old"))
        had = np.unique(u[old].astype(np.int64) * len(x) + v[old])
        bu, bv = _best(np.concatenate([u, v[~old]]), np.concatenate([v, u[~old]]), x, DEGREE)
        new = ~np.isin(bu.astype(np.int64) * len(x) + bv, had)
        shard = np.full(len(bu), points.column("shard")[0].as_py() if len(points) else 0, np.int32)
        return pa.table({"shard": shard, "u": bu, "v": bv, "new": new})

    for t in range(rounds):
        toss = lambda *c: F.xxhash64(F.lit(seed + 1 + t), *c)  # noqa: E731, B023
        pick = Window.partitionBy("shard", "u").orderBy(F.desc("new"), toss("u", "v"), "v")
        few = links.withColumn("r", F.row_number().over(pick)).where(F.col("r") <= SAMPLE)
        ways = few.select("shard", F.col("u").alias("mid"), F.col("v").alias("o"), "new").union(few.select("shard", F.col("v").alias("mid"), F.col("u").alias("o"), "new"))
        spread = Window.partitionBy("shard", "mid").orderBy(toss("o", "mid"), "o", F.desc("new"))
        ways = park(ways.withColumn("r", F.row_number().over(spread)).where(F.col("r") <= 2 * SAMPLE).drop("r"), "ways")
        p, q = ways.alias("p"), ways.alias("q")
        pairs = p.join(q, (F.col("p.shard") == F.col("q.shard")) & (F.col("p.mid") == F.col("q.mid")) & (F.col("p.o") < F.col("q.o")) & (F.col("p.new") | F.col("q.new")))
        pairs = pairs.select(F.col("p.shard").alias("shard"), F.col("p.o").alias("u"), F.col("q.o").alias("v"), F.lit(False).alias("old"))
        tried = pairs.union(links.select("shard", "u", "v", F.lit(True).alias("old")))
        better = park(tried.groupBy("shard").cogroup(nodes.groupBy("shard")).applyInArrow(improve, "shard int, u int, v int, new boolean"), "links")
        drop(links, ways)
        links = better
    return links.select("shard", "u", "v")


def _both_ways(u: np.ndarray, v: np.ndarray, n: int, most: int) -> np.ndarray:
    """Adjacency with links in both directions, at most ``most`` a node (-1: none)."""
    key = np.unique(np.concatenate([u.astype(np.int64) * n + v, v.astype(np.int64) * n + u]))
    a, b = key // n, key % n
    order = np.lexsort((np.random.default_rng(n).random(len(a)), a))
    a, b = a[order], b[order]
    rank = np.arange(len(a)) - np.searchsorted(a, a)
    out = np.full((n, most), -1, np.int64)
    out[a[rank < most], rank[rank < most]] = b[rank < most]
    return out


def search(x: np.ndarray, links: np.ndarray, queries: np.ndarray, own: np.ndarray, top: int, beam: int = BEAM) -> np.ndarray:
    """Greedy search of all queries in step: positions of the ``top`` best found (-1: none).

    own: a query's own position, or -1. Each step expands the ``WIDTH`` best of the beam
    that aren't expanded yet, until every beam is.
    """
    n, nq, low = len(x), len(queries), np.float32(-np.inf)
    beam = min(beam, n)
    entries = np.random.default_rng(n).choice(n, min(n, ENTRIES), replace=False)
    seen = np.zeros((nq, n), bool)
    best, score, done = np.full((nq, beam), -1, np.int64), np.full((nq, beam), low), np.ones((nq, beam), bool)
    fresh = np.concatenate([np.tile(entries, (nq, 1)), np.where(own[:, None] >= 0, links[np.maximum(own, 0)], -1), own[:, None]], axis=1)
    rows = np.arange(nq)[:, None]
    while True:
        fresh = np.sort(fresh, axis=1)
        good = fresh >= 0
        good[:, 1:] &= fresh[:, 1:] != fresh[:, :-1]
        good &= ~seen[rows, np.maximum(fresh, 0)]
        r, c = np.nonzero(good)
        found = fresh[r, c]
        seen[r, found] = True
        s = np.full(fresh.shape, low)
        for i in range(0, len(r), 1 << 17):
            part = slice(i, i + (1 << 17))
            s[r[part], c[part]] = np.einsum("ij,ij->i", queries[r[part]], x[found[part]])
        every, scores, dones = np.concatenate([best, fresh], 1), np.concatenate([score, s], 1), np.concatenate([done, ~good], 1)
        keep = np.argpartition(-scores, beam - 1, axis=1)[:, :beam]
        best, score, done = (np.take_along_axis(a, keep, 1) for a in (every, scores, dones))
        done |= score == low
        waiting = np.where(done, low, score)
        if done.all():
            break
        width = min(WIDTH, beam)
        turn = np.argpartition(-waiting, width - 1, axis=1)[:, :width]
        real = np.take_along_axis(waiting, turn, 1) > low
        np.put_along_axis(done, turn, True, 1)
        at = np.where(real, np.take_along_axis(best, turn, 1), -1)
        fresh = np.where(at[:, :, None] >= 0, links[np.maximum(at, 0)], -1).reshape(nq, -1)
    order = np.argsort(-score, axis=1, kind="stable")[:, :top]
    return np.where(np.take_along_axis(score, order, 1) > low, np.take_along_axis(best, order, 1), -1)


def centroids(x: np.ndarray, k: int, rounds: int = 8, seed: int = 5) -> np.ndarray:
    """k-means over unit vectors, from k of them drawn by seed; an empty cell keeps its centre."""
    c = x[np.random.default_rng(seed).permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        near = np.concatenate([_cell(x[i : i + 8192], c) for i in range(0, len(x), 8192)])
        for j, n in enumerate(np.bincount(near, minlength=len(c))):
            if n:
                c[j] = x[near == j].mean(0)
    return c


def _far(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances to the centres, but for what is the same for all of them."""
    return np.einsum("ij,ij->i", c, c)[None] - 2 * x @ c.T


def _cell(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return _far(x, c).argmin(1)


def _as_query(q: np.ndarray) -> np.ndarray:
    return np.concatenate([q / np.linalg.norm(q, axis=1, keepdims=True), np.zeros((len(q), 1))], axis=1).astype(np.float32)


def brute_force(reps: DataFrame, queries: list[tuple[int, list[float]]], top: int, carry: str) -> DataFrame:
    """query_id, rep, score and ``carry`` of the ``top`` best nodes for a bounded list of queries:
    each task keeps its own best, so few rows move."""
    ids, q = np.array([i for i, _ in queries]), np.array([x for _, x in queries])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, 4096):
            scores = q @ _matrix(b.column("x")).T
            keep = np.argpartition(-scores, min(top, len(b)) - 1, axis=1)[:, :top]
            r = np.repeat(np.arange(len(q)), keep.shape[1])
            at = keep.ravel()
            yield pa.RecordBatch.from_arrays([pa.array(ids[r]), b.column("rep").take(pa.array(at)), pa.array(scores[r, at]), b.column(carry).take(pa.array(at))], names=["query_id", "rep", "score", carry])

    kind = dict(reps.dtypes)[carry]
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "rep")
    found = reps.select("rep", "x", carry).mapInArrow(run, f"query_id long, rep long, score double, {carry} {kind}")
    return found.withColumn("r", F.row_number().over(best)).where(F.col("r") <= top).drop("r")


def nearest(vectors: DataFrame, is_query, top: int = 20, id_col: str = "vec_id", column: str = "embedding", shard: int | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the ``top`` best found for the rows where ``is_query``
    (a condition on vec_id) holds, against all other rows."""
    shard = shard or SHARD
    rows = park(usable(vectors, id_col, column), "vectors")
    reps = park(rows.groupBy("x").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n")), "reps")
    n = reps.count()
    longest = reps.agg(F.max(F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, c: a + c * c)))).head()[0] or 1.0
    same = rows.join(reps.where("n > 1").select("x", "rep"), "x").select("rep", "vec_id")
    few = Window.partitionBy("rep").orderBy("vec_id")
    members = same.withColumn("r", F.row_number().over(few)).where(F.col("r") <= top + 1).select("rep", "vec_id")
    members = park(members.union(reps.where("n = 1").select("rep", F.col("rep").alias("vec_id"))), "members")
    asked = park(rows.where(is_query).join(reps.select("x", "rep"), "x").select(F.col("vec_id").alias("query_id"), "rep", "x"), "asked")

    cells = max(1, min(MAX_CELLS, math.ceil(n / shard)))
    share = max(1, n // FIT_ROWS)
    fitted = reps.where(F.pmod(F.xxhash64(F.lit(9), "rep"), F.lit(share)) == 0).select("x").limit(2 * FIT_ROWS).toArrow() if cells > 1 else None
    centres = centroids(lifted(_matrix(fitted.column("x")), longest), cells) if cells > 1 else None  # MAX_CELLS rows at most

    def celled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, 4096):
            cell = np.zeros(len(b), np.int32) if centres is None else _cell(lifted(_matrix(b.column(1)), longest), centres).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(cell)], names=["rep", "x", "cell"])

    placed = park(reps.select("rep", "x").mapInArrow(celled, "rep long, x array<double>, cell int"), "placed")
    graphs = {r.cell: max(1, math.ceil(r.n / shard)) for r in placed.groupBy("cell").agg(F.count("*").alias("n")).collect()}  # MAX_CELLS rows at most
    first = dict(zip(sorted(graphs), np.cumsum([0] + [graphs[c] for c in sorted(graphs)]).tolist(), strict=False))
    spread = rows.sparkSession.createDataFrame([(c, first[c], graphs[c]) for c in graphs], "cell int, first int, graphs int")
    wide = placed.join(F.broadcast(spread), "cell").select((F.col("first") + F.pmod(F.xxhash64("rep"), F.col("graphs"))).cast("int").alias("shard"), "rep", "x")
    inside = Window.partitionBy("shard")
    nodes = park(wide.select("shard", (F.row_number().over(inside.orderBy("rep", "x")) - 1).alias("i"), F.count("*").over(inside).alias("size"), "rep", "x"), "nodes")
    links = build_graph(nodes, longest)

    probes = 1
    if cells > 1:
        tried = [(r.query_id, list(r.x)) for r in asked.orderBy(F.xxhash64("query_id"), "query_id").limit(PROBES).select("query_id", "x").collect()]
        truth = brute_force(placed, tried, top + 1, "cell").select("query_id", "cell").toArrow() if tried else None
        if tried:
            order = np.argsort(np.argsort(_far(_as_query(np.array([x for _, x in tried])), centres), axis=1), axis=1)
            at = {i: k for k, (i, _) in enumerate(tried)}
            places = np.sort([order[at[i], c] for i, c in zip(truth.column(0).to_pylist(), truth.column(1).to_pylist(), strict=True)])
            probes = int(places[min(len(places) - 1, math.ceil(GOAL * len(places)) - 1)]) + 1

    def routed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, 4096):
            if centres is None:
                near = np.zeros((len(b), 1), np.int64)
            else:
                near = np.argsort(_far(_as_query(_matrix(b.column(2))), centres), axis=1, kind="stable")[:, :probes]
            shards = [[first[c] + k for c in row if c in first for k in range(graphs[c])] for row in near.tolist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(shards, pa.list_(pa.int32()))], names=["query_id", "rep", "x", "shards"])

    sent = asked.mapInArrow(routed, "query_id long, rep long, x array<double>, shards array<int>")
    sent = park(sent.select("query_id", "rep", "x", F.explode("shards").alias("shard")), "sent")
    # a graph is copied once for each block of the queries that it gets, which don't grow with the table
    load = sent.groupBy("shard").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    sent = sent.join(load, "shard").withColumn("block", F.pmod(F.xxhash64("query_id"), F.col("blocks")).cast("int")).drop("blocks")
    lists = links.groupBy("shard", "u").agg(F.collect_list("v").alias("vs"))
    graph = nodes.join(lists, (nodes["shard"] == lists["shard"]) & (nodes["i"] == lists["u"]), "left").select(nodes["shard"], "i", "rep", "x", "vs")
    graph = graph.join(load, "shard").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("blocks")

    def answer(points: pa.Table, queries: pa.Table) -> pa.Table:
        empty = pa.table({"query_id": pa.array([], pa.int64()), "rep": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        if not len(points) or not len(queries):
            return empty
        order = np.argsort(points.column("i").to_numpy())
        full, rep = _matrix(points.column("x"))[order], points.column("rep").to_numpy()[order]
        listed = [points.column("vs")[int(i)].as_py() or [] for i in order]
        u = np.repeat(np.arange(len(full)), [len(v) for v in listed])
        graph = _both_ways(u, np.concatenate([np.array(v, np.int64) for v in listed]) if len(u) else np.empty(0, np.int64), len(full), 2 * DEGREE)
        q = _matrix(queries.column("x"))
        place = {r: i for i, r in enumerate(rep.tolist())}
        own = np.array([place.get(r, -1) for r in queries.column("rep").to_pylist()], np.int64)
        short, points_ = _as_query(q), lifted(full, longest)
        ids, reps_, scores = [], [], []
        for i in range(0, len(q), 512):
            found = search(points_, graph, short[i : i + 512], own[i : i + 512], top + 1)
            r, c = np.nonzero(found >= 0)
            at = found[r, c]
            ids.append(queries.column("query_id").to_numpy()[i + r])
            reps_.append(rep[at])
            scores.append((q[i + r] * full[at]).sum(axis=1))
        return pa.table({"query_id": np.concatenate(ids), "rep": np.concatenate(reps_), "score": np.concatenate(scores)})

    hits = graph.groupBy("shard", "block").cogroup(sent.groupBy("shard", "block")).applyInArrow(answer, "query_id long, rep long, score double")
    hits = park(hits, "hits")
    drop(rows, reps, placed, nodes, asked)
    better = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    out = hits.join(members, "rep").where("vec_id <> query_id").withColumn("rank", F.row_number().over(better))
    return out.where(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")
