"""Ranks by start time and the band of transactions each one overlaps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderproof.operators import prelim
from orderproof.plans.global_order import ranked, running
from orderproof.schema import History
from orderproof.sources.scratch import written


def _below(marks: DataFrame, asked: DataFrame, name: str, strict: bool) -> DataFrame:
    """asked (key, x) with the number of marks (x) below x, or at most x."""
    first = 1 if strict else 0  # on ties a mark counts only where it may equal x
    points = marks.select("x", F.lit(first).alias("o"), F.lit(None).cast("long").alias("key")).unionAll(asked.select("x", F.lit(1 - first).alias("o"), "key"))
    return running(points, "x", ["o"], F.when(F.col("key").isNull(), 1).otherwise(0), "sum", name).filter("key IS NOT NULL").select("key", name)


def bounds(h: History) -> DataFrame:
    """(txn_id, s, e, idx, l, r, wave): place by start; first place whose end is after this start; last place whose start is
    before this end; last place that starts before any later transaction beyond r has ended (r itself where none is)."""
    t = written(ranked(prelim.committed(h).select("txn_id", "s", "e"), "s", ["txn_id"]))
    top = running(t, "s", ["txn_id"], F.col("e"), "max", "top")
    starts = t.select(F.col("s").alias("x"))
    r = _below(starts, t.select(F.col("e").alias("x"), F.col("idx").alias("key")), "r", True)
    low = _below(top.select(F.col("top").alias("x")), t.select(F.col("s").alias("x"), F.col("idx").alias("key")), "l", False)
    back = running(t.withColumn("n", -F.col("idx")), "n", [], -F.col("e"), "max", "m").select(F.col("idx").alias("next"), (-F.col("m")).alias("bound"))
    met = t.join(r.withColumnRenamed("key", "idx"), "idx").join(low.withColumnRenamed("key", "idx"), "idx").withColumn("r", F.col("r") - 1)
    met = written(met)
    met = met.join(back, F.col("next") == F.col("r") + 1, "left")
    wave = _below(starts, met.filter("bound IS NOT NULL").select(F.col("bound").alias("x"), F.col("idx").alias("key")), "wave", True)
    out = met.join(wave.withColumnRenamed("key", "idx"), "idx", "left")
    return written(out.select("txn_id", "s", "e", "idx", "l", "r", F.coalesce(F.col("wave") - 1, F.col("r")).alias("wave")))


def layout(b: DataFrame) -> DataFrame:
    """bounds with the offset of each row in the packed band: the running sum of r - l + 1."""
    return running(b, "idx", [], F.col("r") - F.col("l") + 1, "sum", "ends").withColumn("off", F.col("ends") - (F.col("r") - F.col("l") + 1)).drop("ends")
