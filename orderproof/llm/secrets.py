r"""Secret scan with DataFrame functions only.

Three fixed kinds are found by pattern (assign, access, hex). A fourth, `random`, comes from two character Markov models, one
of random strings and one of ordinary identifiers: a run of 20 or more characters of [A-Za-z0-9+/_=-] that holds a letter,
whose log-likelihood ratio is at least `threshold`, and that no base span touches.

Where a text has n matches of a pattern, split() gives the n+1 gaps between them and regexp_extract_all() the matches, so a
running sum over both gives every position in one pass. Null texts are empty.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.llm.common import free

#: The kinds and their patterns, in the order of the contract.
ASSIGN = r"""((?i)password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"  # a run of 20 or more in all; shorter runs hold no other match
HEX = r"[0-9a-f]{24,}"
ASSIGN_LEAST = 6
KINDS = ("assign", "access", "hex", "random")
#: The characters the models know.
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
RUN = r"[A-Za-z0-9+/_=-]{20,}"
SIDE = len(ALPHABET) + 1  # 0: the start


@dataclass
class RandomnessModel:
    """ratio[a * SIDE + b]: log P(b after a | random) - log P(b after a | identifier); 0 stands for the start."""

    ratio: list[float]
    threshold: float = 12.0

    def score(self, s: Column) -> Column:
        """Log-likelihood ratio of a string over ALPHABET."""
        table = F.split(F.lit(",".join(f"{x:.6g}" for x in self.ratio)), ",").cast("array<double>")

        def step(acc: Column, c: Column) -> Column:
            i = F.instr(F.lit(ALPHABET), c)
            return F.struct(i.alias("p"), (acc["s"] + table[acc["p"] * SIDE + i]).alias("s"))

        return F.aggregate(F.split(s, "", -1), F.struct(F.lit(0).alias("p"), F.lit(0.0).alias("s")), step, lambda acc: acc["s"])


def transitions(samples: DataFrame, column: str = "sample") -> DataFrame:
    """Counts of (a, b) over the labelled samples, a being 0 at a start; characters outside ALPHABET don't count."""
    chars = samples.select(F.split(F.col(column), "", -1).alias("c"))
    idx = chars.select(F.filter(F.transform("c", lambda c: F.instr(F.lit(ALPHABET), c)), lambda i: i > 0).alias("i"))
    pairs = idx.select(F.explode(F.zip_with(F.concat(F.array(F.lit(0)), "i"), F.col("i"), lambda a, b: F.struct(a.alias("a"), b.alias("b")))).alias("p"))
    return pairs.filter("p.b is not null").groupBy("p.a", "p.b").count()


def fit(random: DataFrame, ordinary: DataFrame, threshold: float = 12.0, column: str = "sample", prior: float = 5.0) -> RandomnessModel:
    """Fits both models from labelled samples; what reaches the driver is at most SIDE * SIDE counts a class."""

    def logs(samples: DataFrame) -> list[float]:
        n = [[0.0] * SIDE for _ in range(SIDE)]
        for a, b, k in map(tuple, transitions(samples, column).collect()):
            n[a][b] += k
        one = [0.5 + sum(row[b] for row in n) for b in range(SIDE)]  # an unseen transition backs off to its character
        one = [x / sum(one[1:]) for x in one]
        return [math.log((n[a][b] + prior * one[b]) / (sum(n[a]) + prior)) if b else 0.0 for a in range(SIDE) for b in range(SIDE)]

    return RandomnessModel([x - y for x, y in zip(logs(random), logs(ordinary), strict=True)], threshold)


def random_samples(spark: SparkSession, each: int = 2000) -> DataFrame:
    """Labelled random strings: digests of 0, 1, ... in five alphabets, `each` of every one."""
    raw = spark.range(each).select(F.sha2(F.col("id").cast("string"), 256).alias("h"))
    b64 = F.regexp_replace(F.base64(F.unhex("h")), "=", "")
    b62 = F.translate(b64, "+/", "qZ")
    return raw.select(F.explode(F.array(F.col("h"), b64, b62, F.lower(b62), F.upper(b62))).alias("sample"))


def ordinary_samples(docs: DataFrame, documents: int = 400, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Labelled ordinary identifiers: words of a bounded sample of documents (those with the smallest hash of id), each
    also joined to the next one as snake_case and CamelCase. Words with a digit aren't used."""
    ids = docs.filter(docs[text_col].isNotNull()).select(F.col(id_col).alias("i")).orderBy(F.xxhash64("i", F.lit(7)), "i").limit(documents)
    few = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).join(F.broadcast(ids), "i", "left_semi")
    words = few.select(F.filter(F.split("t", r"[^A-Za-z0-9_-]+", -1), lambda w: (F.length(w) >= 2) & ~w.rlike("[0-9]")).alias("w"))
    pair = F.zip_with(F.col("w"), F.slice(F.col("w"), 2, 1 << 30), lambda a, b: F.array(a, F.concat_ws("_", a, b), F.concat(F.initcap(a), F.initcap(b))))
    return words.select(F.explode(F.flatten(pair)).alias("sample")).filter("sample is not null")


def _matches(text: Column, kind: int, pattern: str, ok) -> Column:
    """array of (kind, at, gap, len, ok) for the leftmost non-overlapping matches of a pattern; empty where there is none."""
    gaps, whole = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    value = F.regexp_extract_all(text, F.lit(pattern), F.lit(2)) if kind == 0 else whole
    both = F.zip_with(whole, value, lambda m, v: F.struct(F.char_length(m).alias("len"), ok(v).alias("ok")))
    found = F.zip_with(gaps, both, lambda g, m: F.struct(F.char_length(g).alias("gap"), m.alias("m")))
    full = F.transform(
        F.filter(found, lambda x: x["m"].isNotNull()),
        lambda x, i: F.struct(F.lit(kind).alias("kind"), i.alias("at"), x["gap"].alias("gap"), x["m"]["len"].alias("len"), x["m"]["ok"].alias("ok")),
    )
    return F.when(text.rlike(pattern), full).otherwise(F.array().cast("array<struct<kind:int,at:int,gap:int,len:int,ok:boolean>>"))


def _tests(model: RandomnessModel):
    yes = lambda v: F.lit(True)
    likely = lambda v: v.rlike("[A-Za-z]") & (model.score(v) >= model.threshold)
    return ((ASSIGN, lambda v: F.char_length(v) >= ASSIGN_LEAST), (ACCESS, yes), (HEX, yes), (RUN, likely))


def find(docs: DataFrame, model: RandomnessModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: id, and spans, an array of (start, kind, end) sorted by start and kind; code points, end exclusive.

    kind: 0 assign, 1 access, 2 hex, 3 random. The texts are read once and don't take part in a shuffle, only the lengths
    of gaps and matches do. Repeated or null ids are rows of their own.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    own = F.array(F.expr("named_struct('kind', cast(null as int), 'at', 0, 'gap', 0, 'len', 0, 'ok', true)"))  # stands for the row
    found = F.concat(own, *(_matches(text, k, p, ok) for k, (p, ok) in enumerate(_tests(model))))
    rows = docs.select(F.col(id_col).alias("id"), F.monotonically_increasing_id().alias("row"), found.alias("found"))
    each = rows.select("id", "row", F.explode("found").alias("m")).select("id", "row", "m.*").repartition("row")
    past = F.sum(F.col("gap") + F.col("len")).over(W.partitionBy("row", "kind").orderBy("at").rowsBetween(W.unboundedPreceding, 0))
    spans = each.withColumn("end", past.cast("long")).withColumn("start", F.col("end") - F.col("len")).filter("ok")
    base = F.col("kind") < 3
    by_start = W.partitionBy("row").orderBy("start", "kind")
    before = F.max(F.when(base, F.col("end"))).over(by_start.rowsBetween(W.unboundedPreceding, -1))
    after = F.min(F.when(base, F.col("start"))).over(by_start.rowsBetween(1, W.unboundedFollowing))
    touched = (F.coalesce(before, F.lit(-1)) > F.col("start")) | (F.coalesce(after, F.col("end")) < F.col("end"))
    keep = F.col("kind").isNotNull() & (base | ~touched)
    kept = spans.withColumn("keep", keep)
    return kept.groupBy("row").agg(
        F.first("id").alias("id"), F.array_sort(F.collect_list(F.when(F.col("keep"), F.struct("start", "kind", "end")))).alias("spans")
    )


def redact(docs: DataFrame, model: RandomnessModel, text_col: str = "text", mask: str = "[SECRET]", count_col: str | None = None) -> DataFrame:
    """docs with every secret in its text replaced by the mask (of an assignment its value only). Other columns, and rows, stay.

    Kind by kind the text is put together again from gaps and matches, which is linear in its length. Null texts stay null. `count_col`, where docs has it, becomes the length of a text that changed.
    """

    def masked(text: Column, kind: int, pattern: str, ok) -> Column:
        gaps, whole = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
        if kind == 0:
            value = F.regexp_extract_all(text, F.lit(pattern), F.lit(2))
            new = F.zip_with(whole, value, lambda m, v: F.when(ok(v), F.concat(F.substr(m, F.lit(1), F.char_length(m) - F.char_length(v)), F.lit(mask))).otherwise(m))
        else:
            new = F.transform(whole, lambda m: F.when(ok(m), F.lit(mask)).otherwise(m))
        return F.when(text.rlike(pattern), F.array_join(F.zip_with(gaps, new, lambda g, m: F.concat(g, F.coalesce(m, F.lit("")))), "")).otherwise(text)

    new = F.col(text_col)
    for kind, (pattern, ok) in enumerate(_tests(model)):
        new = masked(new, kind, pattern, ok)
    if count_col not in docs.columns:
        return docs.withColumn(text_col, new)
    own = free("masked", docs.columns)
    met = docs.withColumn(own, new)
    count = F.when(F.col(own) != F.col(text_col), F.char_length(own).cast(docs.schema[count_col].dataType)).otherwise(F.col(count_col))
    return met.withColumn(count_col, count).withColumn(text_col, F.col(own)).drop(own)


def default_model(docs: DataFrame) -> RandomnessModel:
    return fit(random_samples(docs.sparkSession), ordinary_samples(docs))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = find(docs, default_model(docs))
    name = lambda k: F.element_at(F.array(*map(F.lit, KINDS)), k + 1)
    told = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", name(s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long")
    return found.select(
        F.col("id").alias("doc_id"), count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"),
        F.sha2(told(F.filter("spans", lambda s: s["kind"] < 3)), 256).alias("base_sha256"), told(F.col("spans")).alias("spans"),
    )
