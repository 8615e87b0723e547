"""Approximate nearest neighbours with a vantage-point tree per shard.

Vectors are dealt to shards by id hash; each shard builds a tree whose nodes split their vectors at the
median distance to a vantage point. A block of queries walks a tree together, one visit a node: a
subtree is left out for a query if the triangle inequality, tightened by `factor`, says that it holds
nothing nearer than the query's k-th best so far. With distance d to the vantage point, radius r and
k-th best t, the inner part is skipped if d - r > factor * t and the outer part if r - d > factor * t;
factor 1 is exact, smaller factors prune more. A first greedy descent sets t.

Queries stay a table. They are dealt to blocks of about `BLOCK` by hash, and every pair of a block and a shard is one
task that holds one tree and one block: nothing grows with the data on the driver or in a task. The k best of each
pair are merged per query. Distances are exact, in double precision on original vectors.

Defined results: vectors that are null, all zero or hold null or non-finite components take no part, nor do null ids;
rows of one id and equal vectors are one query, rows of one id with different vectors are queries of their own, each with
its ranks; as candidates, repeated ids are rows of their own, and a query leaves out all rows of its own id; vectors of another
length than the query are no candidates; ties go to smaller ids; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

K = 10
FACTOR = 1.0
LEAF = 64
SHARD_ROWS = 20_000
BLOCK = 8_192


def build(ids: np.ndarray, points: np.ndarray, leaf: int = LEAF) -> list[dict]:
    """Nodes of the tree, the root first; the parts of an inner node are numbers of later nodes."""
    nodes: list[dict] = []
    todo = [(np.arange(len(ids)), None, "")]
    rng = np.random.default_rng(1)
    while todo:
        at, parent, side = todo.pop()
        if parent is not None:
            nodes[parent][side] = len(nodes)
        if len(at) <= leaf:
            nodes.append({"ids": ids[at], "points": points[at]})
            continue
        tries = points[at[rng.integers(0, len(at), 4)]]
        sample = points[at[rng.integers(0, len(at), 64)]]
        spread = [np.sqrt(((sample - p) ** 2).sum(axis=1)).std() for p in tries]
        vantage = tries[int(np.argmax(spread))]
        d = np.sqrt(((points[at] - vantage) ** 2).sum(axis=1))
        radius = float(np.median(d))
        inner = d <= radius
        if inner.all():  # more than half at one distance: cut by number, both parts may hold the radius
            inner = np.zeros(len(at), bool)
            inner[np.argsort(d, kind="stable")[: len(at) // 2]] = True
        nodes.append({"vantage": vantage, "radius": float(d[inner].max()), "outer_from": float(d[~inner].min())})
        todo.append((at[~inner], len(nodes) - 1, "outer"))
        todo.append((at[inner], len(nodes) - 1, "inner"))
    return nodes


class Best:
    """The k nearest so far of every query of a block."""

    def __init__(self, queries: int, k: int) -> None:
        self.d = np.full((queries, k), np.inf)
        self.ids = np.full((queries, k), np.iinfo(np.int64).max)

    def add(self, rows: np.ndarray, d: np.ndarray, ids: np.ndarray) -> None:
        every_d = np.concatenate((self.d[rows], d), axis=1)
        every_id = np.concatenate((self.ids[rows], np.broadcast_to(ids, d.shape)), axis=1)
        order = np.lexsort((every_id, every_d), axis=1)[:, : self.d.shape[1]]
        self.d[rows] = np.take_along_axis(every_d, order, axis=1)
        self.ids[rows] = np.take_along_axis(every_id, order, axis=1)


def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row differences, as exact as doubles are, and equal however queries are put into blocks."""
    return np.sqrt(((a[:, None, :] - b[None, :, :]) ** 2).sum(axis=2))


def search(nodes: list[dict], q_ids: np.ndarray, queries: np.ndarray, k: int, factor: float) -> Best:
    best = Best(len(q_ids), k)
    if not nodes or not len(q_ids):
        return best

    def leaf(node, rows):
        for a in range(0, len(rows), 256):
            part = rows[a : a + 256]
            d = distances(queries[part], node["points"])
            d[q_ids[part][:, None] == node["ids"][None, :]] = np.inf
            best.add(part, d, node["ids"])

    first = {}  # leaf reached by descent -> queries
    todo = [(0, np.arange(len(q_ids)))]
    while todo:
        at, rows = todo.pop()
        node = nodes[at]
        if "ids" in node:
            first[at] = rows
            leaf(node, rows)
            continue
        inner = distances(queries[rows], node["vantage"][None])[:, 0] <= node["radius"]
        for side, part in (("inner", rows[inner]), ("outer", rows[~inner])):
            if len(part):
                todo.append((node[side], part))
    todo = [(0, np.arange(len(q_ids)))]
    while todo:
        at, rows = todo.pop()
        node = nodes[at]
        if "ids" in node:
            done = first.get(at)
            leaf(node, rows if done is None else np.setdiff1d(rows, done))
            continue
        d = distances(queries[rows], node["vantage"][None])[:, 0]
        reach = factor * best.d[rows, -1] * (1 + 1e-12) + 1e-12
        for side, near in (("outer", node["outer_from"] - d <= reach), ("inner", d - node["radius"] <= reach)):
            if near.any():
                todo.append((node[side], rows[near]))
    best.ids[np.isinf(best.d)] = -1
    return best


def usable(df: DataFrame) -> DataFrame:
    """(vec_id, vec) of the vectors that take part, components as doubles."""
    vec = F.col("embedding").cast("array<double>")
    fine = (
        F.col("vec_id").isNotNull()
        & vec.isNotNull()
        & F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
        & F.exists(vec, lambda x: x != 0)
    )
    return df.where(fine).select(F.col("vec_id").cast("long").alias("vec_id"), vec.alias("vec"))


def index(vectors: DataFrame, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(shard, dim, tree): one pickled tree per shard and vector length, about shard_rows rows each."""
    n = vectors.count()
    shards = max(1, -(-n // shard_rows))

    def grow(key, table):
        points = np.stack([np.asarray(x) for x in table.column("vec").to_numpy(zero_copy_only=False)])
        tree = build(table.column("vec_id").to_numpy(), points)
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "dim": pa.array([key[1].as_py()], pa.int32()), "tree": pa.array([pickle.dumps(tree, 5)], pa.binary())})

    dealt = vectors.withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int")).withColumn("dim", F.size("vec"))
    # A repeated id lands in one shard; ids are keys, so shards stay even.
    trees = dealt.groupBy("shard", "dim").applyInArrow(grow, "shard int, dim int, tree binary")
    return materialise(trees, "vp-trees")


def nearest(vectors: DataFrame, queries: DataFrame, k: int = K, factor: float = FACTOR, block: int = BLOCK, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score of the k nearest rows found; both inputs are (vec_id, vec)."""
    trees = index(vectors, shard_rows)
    row = F.xxhash64("vec")  # tells queries of one id apart
    asked = materialise(queries.select("vec_id", "vec", row.alias("q"), F.size("vec").alias("dim")).distinct(), "vp-queries")
    blocks = max(1, -(-asked.count() // block))
    shards = trees.agg(F.max("shard")).first()[0] or 0
    every = asked.withColumn("block", F.pmod(F.xxhash64("vec_id", "q"), F.lit(blocks)).cast("int")).withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards))))
    dealt = trees.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    key = ("shard", "dim", "block")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        ids, q = right.column("vec_id").to_numpy(), right.column("q").to_numpy()
        rows = cols = np.zeros(0, np.int64)
        if left.num_rows and len(ids):
            points = right.column("vec").combine_chunks().flatten().to_numpy().reshape(len(ids), -1)
            best = search(pickle.loads(left.column("tree")[0].as_py()), ids, points, k, factor)
            rows, cols = np.nonzero(np.isfinite(best.d))
        else:
            best = Best(0, k)
        arrays = [pa.array(x) for x in (ids[rows], q[rows], best.ids[rows, cols], best.d[rows, cols])]
        return pa.table(arrays, names=["query_id", "q", "vec_id", "score"])

    found = dealt.groupBy(*key).cogroup(every.groupBy(*key)).applyInArrow(run, "query_id long, q long, vec_id long, score double")
    order = Window.partitionBy("query_id", "q").orderBy("score", "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def search_report(embeddings: DataFrame) -> DataFrame:
    """The contract's query: rows whose id is divisible by 100 against all rows."""
    v = materialise(usable(embeddings), "vp-vectors")
    return nearest(v, v.where(F.col("vec_id") % 100 == 0))

