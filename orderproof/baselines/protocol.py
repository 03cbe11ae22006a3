"""The checker by operation intervals: flags committed updates of one object that overlap in time. It sees no reads."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderproof.operators import constraints, prelim
from orderproof.schema import History


def overlapping_updates(h: History) -> DataFrame:
    """(obj, i, j): committed updates of an object that overlap, from the write operation's begin to its transaction's end: of two such
    the protocol would have let one commit only. A write without an operation time counts from its transaction's begin."""
    last = h.ops.filter("kind = 'w'").groupBy("txn_id", "obj").agg(F.max_by("op_s", "op_seq").alias("op_s"))
    w = last.join(prelim.committed(h).select("txn_id", "s", "e"), "txn_id").select("txn_id", "obj", F.coalesce("op_s", "s").alias("s"), "e")
    return constraints.overlapping(w, ["obj"])


def verify(h: History, protocol: str = "ssi") -> DataFrame:
    """One row: verdict (accept, reject or abstain) and the number of flagged pairs. Without operation times, or for a protocol
    whose rules it doesn't know, it abstains."""
    times = h.ops.agg(F.count("op_s").alias("timed"), F.count("*").alias("ops"))
    flagged = overlapping_updates(h).agg(F.count("*").alias("flagged"))
    one = lambda df: df.withColumn("one", F.lit(1))
    met = one(times).join(one(flagged), "one")
    known = F.lit(protocol in ("ssi", "2pl"))
    verdict = F.when(~known | (F.col("timed") < F.col("ops")), "abstain").when(F.col("flagged") > 0, "reject").otherwise("accept")
    return met.select(verdict.alias("verdict"), "flagged")
