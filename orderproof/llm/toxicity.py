"""Toxicity by non-negative positive-unlabelled learning.

A linear model over hashed word presence is trained with numpy from confirmed toxic documents and a sample of unlabelled
ones. With pi the share of toxic documents, the negative part of the risk is estimated as R_u(-) - pi R_p(-); where a
mini-batch makes it negative its gradient is ascended instead, which keeps a flexible model from fitting that difference below 0.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from orderproof.llm.common import mix64, text_slices, trim, word_hashes, words_of

BITS = 20
STRIP = ".,;:!?|#$%&*()[]{}<>\"'`~_-=+/\\"


def features(text: pa.Array, wanted: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(row, feature), sorted, of the distinct words of each text: lower case, without punctuation at either end, hashed to
    2**BITS. With `wanted` (a truth value per feature) only those."""
    words, rows = words_of(text)
    if not len(words):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    d = words.dictionary_encode()
    bare = pa.array([w.strip(STRIP) for w in d.dictionary.to_pylist()], pa.large_string())
    of = (mix64(word_hashes(bare)) >> np.uint64(64 - BITS)).astype(np.int64)
    feature = of[d.indices.to_numpy()]
    if wanted is not None:
        keep = wanted[feature]
        rows, feature = rows[keep], feature[keep]
    pair = np.unique(rows << BITS | feature)
    return pair >> BITS, pair & ((1 << BITS) - 1)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


@dataclass
class Sparse:
    """Documents as sorted (row, column) pairs over n rows."""

    n: int
    row: np.ndarray
    col: np.ndarray

    def take(self, start: int, stop: int) -> Sparse:
        a, b = np.searchsorted(self.row, [start, stop])
        return Sparse(stop - start, self.row[a:b] - start, self.col[a:b])

    def margin(self, w: np.ndarray, bias: float) -> np.ndarray:
        return bias + np.bincount(self.row, w[self.col], self.n)

    def back(self, g: np.ndarray, size: int) -> tuple[np.ndarray, float]:
        return np.bincount(self.col, g[self.row], size), float(g.sum())


def nnpu(positive: Sparse, unlabelled: Sparse, size: int, prior: float, epochs: int = 60, batches: int = 8, rate: float = 0.02, decay: float = 2e-3) -> tuple[np.ndarray, float, list[float]]:
    """Weights, bias and the risk after each epoch; logistic loss, Adam."""
    w, bias, risks = np.zeros(size), 0.0, []
    m, v, step = np.zeros(size + 1), np.zeros(size + 1), 0
    cut = lambda x, k: (x.n * k // batches, x.n * (k + 1) // batches)
    for _ in range(epochs):
        total = 0.0
        for k in range(batches):
            p, u = positive.take(*cut(positive, k)), unlabelled.take(*cut(unlabelled, k))
            if not p.n or not u.n:
                continue
            mp, mu = p.margin(w, bias), u.margin(w, bias)
            negative = np.logaddexp(0, mu).mean() - prior * np.logaddexp(0, mp).mean()
            total += prior * np.logaddexp(0, -mp).mean() + max(0.0, negative)
            gu, bu = u.back(_sigmoid(mu) / u.n, size)
            if negative >= 0:  # the two terms of the positives add up to a constant slope
                gp, bp = p.back(np.full(p.n, prior / p.n), size)
                g, b = gu - gp, bu - bp
            else:
                gp, bp = p.back(prior * _sigmoid(mp) / p.n, size)
                g, b = gp - gu, bp - bu
            g = np.append(g + decay * w, b)
            step += 1
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
            w, bias = w - move[:-1], bias - move[-1]
        risks.append(total / batches)
    return w, bias, risks


def calibrated(margin: np.ndarray, label: np.ndarray, steps: int = 50) -> tuple[float, float]:
    """Slope (not below 0) and intercept of a one-dimensional logistic fit, by Newton steps with a small ridge."""
    a, b = 1.0, 0.0
    for _ in range(steps):
        p = _sigmoid(a * margin + b)
        g = np.array([((p - label) * margin).sum() + 1e-3 * a, (p - label).sum() + 1e-3 * b])
        r = p * (1 - p)
        h = np.array([[(r * margin * margin).sum() + 1e-3, (r * margin).sum()], [(r * margin).sum(), r.sum() + 1e-3]])
        d = np.linalg.solve(h, g)
        a, b = max(0.0, a - d[0]), b - d[1]
        if abs(d).max() < 1e-8:
            break
    return a, b


@dataclass
class ToxicityModel:
    weights: np.ndarray
    bias: float
    slope: float
    intercept: float
    risks: list[float]

    def scores(self, text: pa.Array) -> np.ndarray:
        out = []
        for part in text_slices(pa.RecordBatch.from_arrays([text], ["text"])):
            row, col = features(part.column(0), self.weights != 0)
            out.append(_sigmoid(self.slope * Sparse(part.num_rows, row, col).margin(self.weights, self.bias) + self.intercept))
        return np.concatenate(out) if out else np.zeros(0)

    def score(self, text: Column) -> Column:
        """Score of 0 to 1 of a text column; a null or empty text has the score of a text without words."""
        model = self

        @F.arrow_udf("double")
        def toxic(text: pa.Array) -> pa.Array:
            out = pa.array(model.scores(text))
            trim()
            return out

        return toxic(text)


def _sparse(table: pa.Table, size: int | None = None) -> Sparse:
    lists = table["f"].combine_chunks()
    return Sparse(len(lists), np.repeat(np.arange(len(lists)), lists.value_lengths().to_numpy(zero_copy_only=False)), lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64))


def fit(
    docs: DataFrame, labels: DataFrame, eligible: Column | None = None, positives: int = 4000, unlabelled: int = 12_000, least_docs: int = 4, least_z: float = 4.0
) -> ToxicityModel:
    """Trains from docs (doc_id, text) and labels (doc_id, toxic) whose doc_id meets `eligible`.

    Bounded samples, by smallest hash of doc_id: `positives` confirmed toxic documents, `unlabelled` documents of any kind (their
    labels play no part in the risk), and as many labelled ones, toxic or not, for the class prior and the calibration: the risk is
    learnt from positives and unlabelled texts only, the prior and the two numbers that map margins to scores are not. Rows with a
    null id or label don't train. Of several labels of a doc_id the largest holds; of several texts each is a row. With no toxic label at all every text scores 0.
    """
    ok = F.lit(True) if eligible is None else eligible
    by = F.xxhash64(F.col("doc_id"), F.lit(11))
    known = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).filter(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ok).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    some = lambda df, n: df.orderBy(by, "doc_id").limit(n)
    toxic = some(known.filter("toxic = 1"), positives).select("doc_id", F.lit(1).alias("use"), F.lit(1).alias("toxic"))
    told = some(known, unlabelled).select("doc_id", F.lit(2).alias("use"), "toxic")
    other = some(docs.select("doc_id").filter(F.col("doc_id").isNotNull() & ok), unlabelled).select("doc_id", F.lit(0).alias("use"), F.lit(0).alias("toxic"))

    @F.arrow_udf("array<int>")
    def hashed(text: pa.Array) -> pa.Array:
        sizes, flat = [], []
        for part in text_slices(pa.RecordBatch.from_arrays([text], ["text"])):
            row, col = features(part.column(0))
            sizes.append(np.bincount(row, minlength=part.num_rows))
            flat.append(col)
        ends = np.concatenate([[0], np.cumsum(np.concatenate(sizes))]) if sizes else np.zeros(1)
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(flat) if flat else [], pa.int32()))

    ids = F.broadcast(toxic.union(told).union(other).groupBy("doc_id").agg(F.collect_set(F.struct("use", "toxic")).alias("uses")))
    rows = docs.select("doc_id", "text").join(ids, "doc_id").select("doc_id", "uses", hashed("text").alias("f"))
    table = rows.toArrow().sort_by("doc_id")
    uses = table["uses"].to_pylist()
    pick = lambda k: np.array([any(u["use"] == k for u in us) for us in uses], bool)
    part = lambda mask: _sparse(table.filter(pa.array(mask, pa.bool_())))
    p, u, t = part(pick(1)), part(pick(0)), part(pick(2))
    label = np.array([x["toxic"] for us in uses for x in us if x["use"] == 2], float)
    full = np.zeros(1 << BITS)
    if not p.n or not u.n:
        return ToxicityModel(full, -20.0, 1.0, 0.0, [])
    prior = float(np.clip(label.mean(), 0.001, 0.9))
    # features whose document shares differ clearly between toxic and unlabelled documents
    np_, nu = np.bincount(p.col, minlength=1 << BITS), np.bincount(u.col, minlength=1 << BITS)
    share = (np_ + nu) / (p.n + u.n)
    z = np.abs(np_ / p.n - nu / u.n) / np.sqrt(np.maximum(share * (1 - share), 1e-12) * (1 / p.n + 1 / u.n))
    chosen = np.flatnonzero((z >= least_z) & (np_ + nu >= least_docs))
    at = np.full(1 << BITS, -1)
    at[chosen] = np.arange(len(chosen))

    def over(x: Sparse) -> Sparse:
        keep = at[x.col] >= 0
        return Sparse(x.n, x.row[keep], at[x.col[keep]])

    w, bias, risks = nnpu(over(p), over(u), len(chosen), prior)
    full[chosen] = w
    slope, intercept = calibrated(over(t).margin(w, bias), label)
    return ToxicityModel(full, bias, slope, intercept, risks)


def remainder(doc_id: Column, n: int) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % n


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    held_out = remainder(F.col("doc_id"), 4) == 2
    model = fit(docs, labels, ~held_out)
    scored = docs.select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), model.score(F.col("text")).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.3).cast("int"))
