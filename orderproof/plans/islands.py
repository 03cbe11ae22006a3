"""Cuts of a history that no cycle crosses.

In start order every time edge points forward, so a cycle needs an edge that points back and stays within what such edges span.
A gap between two places that no backward edge, and no constraint, spans cuts the history. Quiescent gaps are a special case.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderproof.plans.global_order import running
from orderproof.sources.scratch import written


def assign(b: DataFrame, spans: DataFrame) -> DataFrame:
    """b (txn_id, idx, ...) with island, the first place of each one; spans: (low, high) places that lie in one island."""
    reach = spans.filter("high > low").groupBy(F.col("low").alias("idx")).agg(F.max("high").alias("to"))
    met = b.join(reach, "idx", "left").withColumn("to", F.greatest(F.coalesce("to", "idx"), "idx"))
    upto = written(running(met, "idx", [], F.col("to"), "max", "covered"))
    # an island begins where nothing before reaches
    before = upto.select((F.col("idx") + 1).alias("idx"), F.col("covered").alias("earlier"))
    starts = upto.join(before, "idx", "left").withColumn("start", F.when(F.coalesce("earlier", F.lit(-1)) < F.col("idx"), F.col("idx")).otherwise(F.lit(-1)))
    return written(running(written(starts), "idx", [], F.col("start"), "max", "island").drop("to", "covered", "earlier", "start"))


def epochs(b: DataFrame) -> DataFrame:
    """b with epoch: the quiescent stretches, between which no transaction is open."""
    return assign(b, b.select(F.col("idx").alias("low"), F.col("r").alias("high"))).withColumnRenamed("island", "epoch")
