"""Anomalies put into a history that is serializable: each makes it unserializable by itself."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.operators import prelim
from orderproof.schema import INITIAL, History


def _new(h: History, txns: list[tuple], ops: list[tuple]) -> History:
    spark = h.txns.sparkSession
    t = spark.createDataFrame([(i, -1, k, "c", s, e, "injected") for k, (i, s, e) in enumerate(txns)], h.txns.schema)
    o = spark.createDataFrame([(i, k, kind, obj, ver, None, None, None) for k, (i, kind, obj, ver) in enumerate(ops)], h.ops.schema)
    return h.but(txns=h.txns.unionAll(t), ops=h.ops.unionByName(o))


def _end(h: History) -> tuple[int, int, int]:
    """(last end, largest transaction id, largest version)."""
    e, t = h.txns.agg(F.max("e"), F.max("txn_id")).head()
    return e or 0, t or 0, h.ops.agg(F.max("ver")).head()[0] or 0


def stale_read(h: History, k: int = 1) -> History:
    """k reads see the version before the one they saw, though the writer of that had ended before the reader began."""
    w = prelim.installed(h)
    order = w.withColumn("older", F.coalesce(F.lag("ver").over(W.partitionBy("obj").orderBy("e", "txn_id")), F.lit(INITIAL)).cast("long")).select("obj", "ver", "older", F.col("e").alias("we"))
    reads = h.ops.filter("kind = 'r'").join(prelim.committed(h).select("txn_id", "s"), "txn_id").join(order, ["obj", "ver"]).filter("we <= s")
    few = reads.orderBy(F.xxhash64("txn_id", "op_seq"), "txn_id", "op_seq").limit(k).select("txn_id", "op_seq", "obj", "older")
    ops = h.ops.join(F.broadcast(few), ["txn_id", "op_seq", "obj"], "left").withColumn("ver", F.when(F.col("kind") == "r", F.coalesce("older", "ver")).otherwise(F.col("ver")))
    return h.but(ops=ops.select(*h.ops.columns))


def _last(h: History) -> tuple[str, int]:
    """An object and its last version."""
    r = prelim.installed(h).orderBy(F.desc("e"), F.desc("txn_id"), "obj").select("obj", "ver").head()
    return r.obj, r.ver


def lost_update(h: History, k: int = 1) -> History:
    """k times two transactions, after all others, that read the same version of an object and write it."""
    (e, t, v), (obj, last) = _end(h), _last(h)
    txns, ops = [], []
    for n in range(k):
        at, a, own, see = e + 1000 * (n + 1), t + 2 * n + 1, (obj if not n else f"injected:{n}"), (last if not n else INITIAL)
        txns += [(a, at, at + 100), (a + 1, at + 1, at + 101)]
        for x in (a, a + 1):
            v += 1
            ops += [(x, "r", own, see), (x, "w", own, v)]
    return _new(h, txns, ops)


def write_skew(h: History, k: int = 1) -> History:
    """k times two transactions that read two objects and write one each."""
    e, t, v = _end(h)
    txns, ops = [], []
    for n in range(k):
        at, a = e + 1000 * (n + 1), t + 2 * n + 1
        x, y = f"injected:{n}a", f"injected:{n}b"
        txns += [(a, at, at + 100), (a + 1, at + 1, at + 101)]
        ops += [(a, "r", x, INITIAL), (a, "r", y, INITIAL), (a, "w", x, v + 1), (a + 1, "r", x, INITIAL), (a + 1, "r", y, INITIAL), (a + 1, "w", y, v + 2)]
        v += 2
    return _new(h, txns, ops)


def aborted_read(h: History, k: int = 1) -> History:
    """The writers of k versions that others read abort."""
    seen = prelim.reads(h).select("obj", "ver", F.col("txn_id").alias("reader"))
    w = prelim.installed(h).join(seen, ["obj", "ver"]).filter("reader <> txn_id").select("txn_id").distinct()
    few = w.orderBy(F.xxhash64("txn_id"), "txn_id").limit(k).withColumn("gone", F.lit(True))
    return h.but(txns=h.txns.join(F.broadcast(few), "txn_id", "left").withColumn("status", F.when(F.col("gone"), "a").otherwise(F.col("status"))).select(*h.txns.columns))


KINDS = {"stale_read": stale_read, "lost_update": lost_update, "write_skew": write_skew, "aborted_read": aborted_read}


def apply(h: History, kind: str, k: int = 1) -> History:
    return KINDS[kind](h, k)


def changed(before: History, after: History) -> DataFrame:
    """Operations that an injection added or changed."""
    return after.ops.exceptAll(before.ops)
