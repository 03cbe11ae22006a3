"""Histories over the given tables, and fixtures, as History bundles."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from orderproof import schema
from orderproof.histories import texts
from orderproof.operators import dense
from orderproof.plans.global_order import running_all
from orderproof.schema import History
from orderproof.sources import generator
from orderproof.sources.scratch import written
from orderproof.sources.tables import views


def named(ctes: str) -> str:
    """The text over the views that tables.views() makes."""
    return re.sub(r"\b(FROM|JOIN|events,) (events|part|orders|lineitem|customer)\b", r"\1 orderproof_\2", ctes)


def _of(spark: SparkSession, ctes: str) -> History:
    ctes = named(ctes)
    txns = spark.sql(f"WITH {ctes} SELECT txn_id, session_id, session_pos, status, s, e, ttype FROM txns")
    ops = spark.sql(f"WITH {ctes} SELECT txn_id, op_seq, kind, obj, ver, cast(null AS int) AS pred_id, op_s, op_e FROM ops")
    return History(txns, ops)


def registers(spark: SparkSession, sf_dir: str, mix: str = "wr", level: str = "serial") -> History:
    views(spark, sf_dir, "events", "part")
    return _of(spark, texts.registers("spark", mix, level))


def orders_mix(spark: SparkSession, sf_dir: str) -> History:
    views(spark, sf_dir, "orders", "lineitem")
    return _of(spark, texts.orders_mix("spark"))


def social(spark: SparkSession, sf_dir: str) -> History:
    views(spark, sf_dir, "events")
    return _of(spark, texts.social("spark"))


def inline(spark: SparkSession, txns: list[tuple], ops: list[tuple], vers: list[tuple] = (), preds: list[tuple] = ()) -> History:
    """From rows: txns (txn_id, s, e[, status[, session_id, session_pos]]), ops (txn_id, kind, obj, ver[, pred_id]), vers (obj, ver,
    txn_id, v1), preds (pred_id, domain, lo, hi) over v1."""
    t = [(x[0], x[4] if len(x) > 4 else x[0], x[5] if len(x) > 5 else 0, x[3] if len(x) > 3 else "c", x[1], x[2], "fixture") for x in txns]
    o = [(x[0], k, x[1], x[2], x[3], x[4] if len(x) > 4 else None, None, None) for k, x in enumerate(ops)]
    v = [(x[0], x[1], x[2], float(x[3]), None, False) for x in vers]
    p = [(x[0], x[1], "v1", float(x[2]), float(x[3])) for x in preds]
    make = lambda rows, kind: spark.createDataFrame(list(rows), kind)
    return History(make(t, schema.TXNS), make(o, schema.OPS), make(v, schema.VERS), make(p, schema.PREDS))


def prefix(h: History, n: int) -> History:
    """The n transactions that start first, with their operations."""
    few = h.txns.orderBy("s", "txn_id").limit(n)
    return h.but(txns=few, ops=h.ops.join(F.broadcast(few.select("txn_id")) if n <= 100_000 else few.select("txn_id"), "txn_id", "left_semi"))


def widened(h: History, latency_us: int = 0, skew_us: int = 0) -> History:
    """Client intervals widened by network latency and by a bound on clock skew."""
    pad = latency_us + skew_us
    return h.but(txns=h.txns.withColumn("s", F.col("s") - pad).withColumn("e", F.col("e") + pad))


def generated(spark: SparkSession, rows: int, objects: int = 10_000, writers: int = 5) -> History:
    """A register history of any size from the generating source; reads see the last version by the order of end times."""
    generator.register(spark)
    asked = spark.read.format("register_history").options(rows=rows, objects=objects, writers=writers).load()
    seen = running_all(asked.withColumn("own", F.when(F.col("kind") == "w", F.struct("e", "txn_id", "op_seq", "ver"))), "e", ["txn_id", "op_seq"], {"last": ("max", F.col("own"), True)}, ["obj"])
    none = lambda kind: F.lit(None).cast(kind)
    ops = seen.select("txn_id", "op_seq", "kind", "obj", F.coalesce("ver", "last.ver", F.lit(0)).cast("long").alias("ver"), none("int").alias("pred_id"), none("long").alias("op_s"), none("long").alias("op_e"))
    txns = asked.groupBy("txn_id").agg(F.min("s").alias("s"), F.max("e").alias("e"), F.max("kind").alias("ttype"))
    txns = txns.select("txn_id", (F.col("txn_id") % 24).cast("int").alias("session_id"), F.floor(F.col("txn_id") / 24).cast("int").alias("session_pos"), F.lit("c").alias("status"), "s", "e", "ttype")
    return History(txns, ops)


def predicate_rows(spark: SparkSession, sf_dir: str, reads: bool | str = True) -> History:
    """The history of texts.predicate_rows(); what its predicate reads return is found object by object, once for all that use it.
    Without `reads` it has no predicate reads, for what asks of predicates and versions only; with "asked" they return nothing, for what
    completes the history itself, and with "packed" what they return is packed by object, see History.returned."""
    views(spark, sf_dir, "events", "part")
    objects, events, follows = (named(x) for x in texts.predicate_parts("spark"))
    # the operations are sorted once for all tables that follow from them
    op1 = written(spark.sql(f"WITH {objects}, {events} SELECT event_id, o, session_id, txn_id, block, kind, s, e, op_seq, a1, a2, which FROM op1"))
    op1.createOrReplaceTempView("orderproof_op1")
    ctes = f"{objects}, op1 AS (SELECT * FROM orderproof_op1), {follows}"
    get = lambda what, table: written(spark.sql(f"WITH {ctes} SELECT {what} FROM {table}"))
    preds = get("pred_id, domain, col, lo, hi", "prs")
    wrote = get("txn_id, cast(op_seq AS int) AS op_seq, kind, concat('prow:', cast(o AS string)) AS obj, event_id + 1 AS ver, cast(null AS int) AS pred_id", "op1 WHERE kind = 'w'")
    txns, vers = get("txn_id, session_id, session_pos, status, s, e, ttype", "txns"), get("obj, ver, txn_id, v1, v2, deleted", "vers")
    times = lambda df: df.select("*", none("long").alias("op_s"), none("long").alias("op_e"))
    none = lambda kind: F.lit(None).cast(kind)
    if not reads:
        return History(txns, times(wrote), vers, preds)
    row = lambda df, obj, ver: df.select("txn_id", F.lit(0).alias("op_seq"), F.lit("pr").alias("kind"), obj.alias("obj"), ver.alias("ver"), F.col("pred_id").cast("int").alias("pred_id"))
    asks = get("txn_id, e, pred_id, 'prow' AS domain, col, lo, hi", "asked")
    if reads == "asked":
        return History(txns, times(row(asks, none("string"), none("long")).unionByName(wrote)), vers, preds)
    shown = get("obj, ver, e, txn_id, v1, v2, next_e, next_txn", "shown")
    if reads == "packed":
        packed, made = dense.hits_made(asks.withColumn("s", F.col("e")), shown)
        return History(txns, times(row(asks, none("string"), none("long")).unionByName(wrote)), vers, preds, packed, made)
    hits, made = dense.hits_made(asks.withColumn("s", F.col("e")), shown, packed=False)
    missed = row(asks.join(dense.returning(asks, made), ["txn_id", "pred_id"], "left_anti"), none("string"), none("long"))
    return History(txns, times(row(hits, F.col("obj"), F.col("ver")).unionByName(missed).unionByName(wrote)), vers, preds)
