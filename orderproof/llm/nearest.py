"""Approximate nearest neighbours by stable projections.

Vectors are projected to `m` Gaussian directions: for two vectors at distance d the squared projected distance is d^2 times a
chi-square variable with m degrees of freedom. A kd-tree over the projections gives a query's projected neighbours one after
the other, nearest first; each is verified on the original vectors. It stops where a vector nearer than the k-th best would
have come by now with probability `sure`.

The tree's upper levels, fitted on a bounded sample, deal all vectors into blocks; each block holds a tree of its own. A query is
searched in its own block first, which bounds the k-th distance, and then in those blocks whose boxes the same test doesn't
rule out. Equal vectors are one entry with its k + 1 smallest ids, and equal queries are searched once.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.llm.common import staged

LEAF = 128


def chi_square_below(x: float, m: int) -> float:
    """P(chi-square with m degrees, m even, is at most x)."""
    if x <= 0:
        return 0.0
    half, term, total = x / 2, 1.0, 1.0
    for i in range(1, m // 2):
        term *= half / i
        total += term
    return 1.0 - math.exp(-half) * total


def chi_square_quantile(p: float, m: int) -> float:
    low, high = 0.0, 1000.0
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if chi_square_below(mid, m) < p else (low, mid)
    return high


def directions(dim: int, m: int, seed: int = 17) -> np.ndarray:
    return np.random.default_rng(seed).normal(size=(dim, m))


class Tree:
    """kd-tree over projected points: leaves of at most LEAF points with their boxes."""

    def __init__(self, points: np.ndarray):
        self.points, leaves, todo = points, [], [np.arange(len(points))]
        while todo:
            at = todo.pop()
            if len(at) <= LEAF:
                leaves.append(at)
                continue
            x = points[at]
            axis = int(np.argmax(x.max(0) - x.min(0)))
            order = np.argpartition(x[:, axis], len(at) // 2)
            todo += [at[order[: len(at) // 2]], at[order[len(at) // 2 :]]]
        self.leaves = [x for x in leaves if len(x)]
        self.low = np.array([points[x].min(0) for x in self.leaves])
        self.high = np.array([points[x].max(0) for x in self.leaves])

    def nearest_first(self, q: np.ndarray, most=lambda: math.inf):
        """(squared projected distances, indexes) in batches, never a farther point before a nearer one; ends beyond most()."""
        gap = np.maximum(np.maximum(self.low - q, q - self.high), 0)
        box = (gap * gap).sum(1)
        order = np.argsort(box, kind="stable")
        d, at = np.zeros(0), np.zeros(0, np.int64)
        for k, leaf in enumerate(order):
            x = self.points[self.leaves[leaf]] - q
            d, at = np.concatenate([d, (x * x).sum(1)]), np.concatenate([at, self.leaves[leaf]])
            bound = box[order[k + 1]] if k + 1 < len(order) else math.inf
            now = d <= bound
            if now.any():
                by = np.argsort(d[now], kind="stable")
                yield d[now][by], at[now][by]
                d, at = d[~now], at[~now]
            if bound > most():
                return


def search(tree: Tree, vectors: np.ndarray, ids: list, q: np.ndarray, pq: np.ndarray, k: int, quantile: float, bound: float) -> list[tuple[float, int]]:
    """Up to k (distance, id) of one block, nearest first; `bound` is a k-th distance already known. Distances in double precision."""
    best: list[tuple[float, int]] = []
    kth = bound

    def most() -> float:
        return quantile * kth * kth

    for d, at in tree.nearest_first(pq, most):
        for a in range(0, len(at), 64):
            if d[a] > most():
                return best
            part = at[a : a + 64]
            x = vectors[part].astype(np.float64) - q
            far = np.sqrt((x * x).sum(1))
            near = far <= kth
            for f, i in zip(far[near].tolist(), part[near].tolist(), strict=True):
                best += [(f, v) for v in ids[i]]
            if near.any():
                best = sorted(best)[:k]
                if len(best) == k:
                    kth = min(kth, best[-1][0])
    return best


class Splits:
    """Upper levels of the tree: axes and values by heap position, fitted on a sample of projected points."""

    def __init__(self, sample: np.ndarray, depth: int):
        self.depth, self.m = depth, sample.shape[1]
        self.axis, self.value = np.zeros(1 << depth, np.int64), np.zeros(1 << depth)
        self.low, self.high = np.full((1 << depth, self.m), -np.inf), np.full((1 << depth, self.m), np.inf)
        todo = [(1, sample, self.low[0].copy(), self.high[0].copy())]
        while todo:
            at, x, low, high = todo.pop()
            if at >= 1 << depth:
                self.low[at - (1 << depth)], self.high[at - (1 << depth)] = low, high
                continue
            axis = int(np.argmax(x.std(0))) if len(x) else 0
            value = float(np.median(x[:, axis])) if len(x) else 0.0
            self.axis[at], self.value[at] = axis, value
            left = x[:, axis] <= value
            below, above = high.copy(), low.copy()
            below[axis], above[axis] = min(high[axis], value), max(low[axis], value)
            todo += [(2 * at, x[left], low, below), (2 * at + 1, x[~left], above, high)]

    def of(self, x: np.ndarray) -> np.ndarray:
        at = np.ones(len(x), np.int64)
        for _ in range(self.depth):
            at = 2 * at + (x[np.arange(len(x)), self.axis[at]] > self.value[at])
        return at - (1 << self.depth)

    def gaps(self, q: np.ndarray) -> np.ndarray:
        """Squared distance of a projected point to every block's box."""
        g = np.maximum(np.maximum(self.low - q, q - self.high), 0)
        return (g * g).sum(1)


def _matrix(a: pa.ChunkedArray | pa.Array, dim: int) -> np.ndarray:
    a = a.combine_chunks() if isinstance(a, pa.ChunkedArray) else a
    return a.flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)


def neighbours(
    vectors: DataFrame, is_query, k: int = 10, m: int = 8, sure: float = 0.97, block: int = 16_384, sample: int = 20_000, most_blocks: int = 4096,
    id_col: str = "vec_id", vector_col: str = "embedding",
) -> DataFrame:
    """(query_id, rank, id, score): the k nearest found of each row that meets `is_query`, among rows of another id; by distance,
    ties to the smaller id; fewer where there are fewer.

    Vectors that are null, zero, or hold a null, NaN or infinity take no part, nor do those whose length isn't the most
    common one, nor rows with a null id. The splits are fitted on `sample` distinct vectors with the smallest hashes; every
    vector is indexed. Blocks are dealt into tasks of about `block` vectors however the splits fall.
    """
    spark = vectors.sparkSession
    v = F.col("v")
    fine = F.size(v) > 0
    fine &= ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("v"), F.coalesce(is_query, F.lit(False)).alias("q")).filter(F.col("id").isNotNull() & v.isNotNull()).filter(fine)
    dims = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    schema = "query_id long, rank int, id long, score double"
    if not dims:
        return spark.createDataFrame([], schema)
    dim, total = dims[0]
    rows = rows.filter(F.size("v") == dim).withColumn("v", F.transform("v", lambda x: x.cast("double") + F.lit(0.0)))
    few = W.partitionBy("v").orderBy("id")
    entries = rows.select("id", "v").distinct().withColumn("r", F.row_number().over(few)).filter(F.col("r") <= k + 1).groupBy("v").agg(F.array_sort(F.collect_list("id")).alias("ids"))
    project = directions(dim, m)
    first = np.array([r.v for r in entries.select("v").orderBy(F.xxhash64("v")).limit(sample).collect()]) @ project
    splits = Splits(first, max(0, min(most_blocks, total // block).bit_length()))
    chi = chi_square_quantile(sure, m)

    @F.arrow_udf("int")
    def home(v: pa.Array) -> pa.Array:
        return pa.array(splits.of(_matrix(v, dim) @ project).astype(np.int32))

    entries = staged(entries.withColumn("block", home("v")), "entries")
    sizes = entries.groupBy("block").count().withColumn("parts", F.ceil(F.col("count") / block).cast("int")).select("block", "parts")
    dealt = entries.join(F.broadcast(sizes), "block").withColumn("part", F.pmod(F.xxhash64("ids"), "parts").cast("int"))  # a row a block, most_blocks * 2 at most
    queries = staged(rows.filter("q").groupBy("v").agg(F.min("id").alias("name")).withColumn("block", home("v")), "queries")

    def parts_of(asked: DataFrame) -> DataFrame:
        return asked.join(F.broadcast(sizes), "block").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))

    def searched(asked: DataFrame) -> DataFrame:
        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            out = [[], [], []]
            if left.num_rows and right.num_rows:
                x, ids = _matrix(left["v"], dim), left["ids"].to_pylist()
                tree = Tree(x @ project)
                q = _matrix(right["v"], dim)
                pq = q @ project
                for i, (name, bound) in enumerate(zip(right["name"].to_pylist(), right["bound"].to_pylist(), strict=True)):
                    for d, v in search(tree, x, ids, q[i], pq[i], k + 1, chi, bound):
                        for c, y in zip(out, (name, v, d), strict=True):
                            c.append(y)
            return pa.table(out, pa.schema([("name", pa.int64()), ("id", pa.int64()), ("score", pa.float64())]))

        return dealt.select("block", "part", "v", "ids").groupBy("block", "part").cogroup(asked.select("block", "part", "v", "name", "bound").groupBy("block", "part")).applyInArrow(run, "name long, id long, score double")

    near = staged(searched(parts_of(queries.withColumn("bound", F.lit(float("inf"))))), "near")
    by_name = W.partitionBy("name").orderBy("score", "id")
    bounds = near.withColumn("r", F.row_number().over(by_name)).filter(F.col("r") == k + 1).select("name", F.col("score").alias("bound"))
    bounded = queries.join(bounds, "name", "left").withColumn("bound", F.coalesce("bound", F.lit(float("inf"))))

    @F.arrow_udf("array<int>")
    def open_blocks(v: pa.Array, own: pa.Array, bound: pa.Array) -> pa.Array:
        p = _matrix(v, dim) @ project
        out = []
        for x, o, b in zip(p, own.to_pylist(), bound.to_pylist(), strict=True):
            at = np.flatnonzero(splits.gaps(x) <= chi * b * b)
            out.append([int(i) for i in at if i != o])
        return pa.array(out, pa.list_(pa.int32()))

    others = bounded.withColumn("block", F.explode(open_blocks("v", "block", "bound")))
    found = staged(near.unionAll(searched(parts_of(others))), "found")
    top = found.withColumn("r", F.row_number().over(by_name)).filter(F.col("r") <= k + 1).groupBy("name").agg(F.array_sort(F.collect_list(F.struct("score", "id"))).alias("top"))
    asked = rows.filter("q").join(queries.select("v", "name"), "v").join(top, "name").select(F.col("id").alias("query_id"), "top")
    others = F.slice(F.filter("top", lambda t: t["id"] != F.col("query_id")), 1, k)
    return asked.select("query_id", F.posexplode(others).alias("pos", "t")).select("query_id", (F.col("pos") + 1).cast("int").alias("rank"), F.col("t.id").alias("id"), F.col("t.score").alias("score"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return neighbours(rows, F.col("vec_id") % 100 == 0).withColumnRenamed("id", "vec_id")
