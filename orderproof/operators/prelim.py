"""What can be read off a history directly: committed and installed data, invalid reads, and predicates on versions.

Every equi-join is on (obj, ver) or txn_id; nothing here is quadratic.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.schema import INITIAL, History


def committed(h: History) -> DataFrame:
    return h.txns.filter("status = 'c'")


def writes(h: History) -> DataFrame:
    """All writes with their transaction's status and times."""
    return h.ops.filter("kind = 'w'").join(h.txns.select("txn_id", "status", "s", "e"), "txn_id")


def installed(h: History) -> DataFrame:
    """(txn_id, obj, ver, s, e): the last write of each committed transaction to each object."""
    last = h.ops.filter("kind = 'w'").groupBy("txn_id", "obj").agg(F.max_by("ver", "op_seq").alias("ver"))
    return last.join(committed(h).select("txn_id", "s", "e"), "txn_id").select("txn_id", "obj", "ver", "s", "e")


def reads(h: History) -> DataFrame:
    """(txn_id, obj, ver, s, e): distinct reads, item or predicate, of known versions by committed transactions."""
    seen = h.ops.filter("kind <> 'w' AND ver IS NOT NULL").select("txn_id", "obj", "ver").distinct()
    return seen.join(committed(h).select("txn_id", "s", "e"), "txn_id")


def aborted_reads(h: History) -> DataFrame:
    """(reader, writer, obj, ver) where a committed transaction saw a write of an aborted one."""
    bad = writes(h).filter("status = 'a'").select(F.col("txn_id").alias("writer"), "obj", "ver")
    return reads(h).join(bad, ["obj", "ver"]).select(F.col("txn_id").alias("reader"), "writer", "obj", "ver")


def intermediate_reads(h: History) -> DataFrame:
    """(reader, writer, obj, ver) where another committed transaction's write was seen that it later overwrote itself."""
    w = writes(h).filter("status = 'c'").select(F.col("txn_id").alias("writer"), "obj", "ver")
    over = w.join(installed(h).select(F.col("txn_id").alias("writer"), "obj", "ver"), ["writer", "obj", "ver"], "left_anti")
    return reads(h).join(over, ["obj", "ver"]).filter("txn_id <> writer").select(F.col("txn_id").alias("reader"), "writer", "obj", "ver").distinct()


def orphan_reads(h: History) -> DataFrame:
    """(reader, obj, ver) where nobody wrote the version; version 0 is the initial one."""
    return reads(h).filter(F.col("ver") != INITIAL).join(h.ops.filter("kind = 'w'").select("obj", "ver"), ["obj", "ver"], "left_anti").select(F.col("txn_id").alias("reader"), "obj", "ver")


def own_reads(h: History) -> DataFrame:
    """(reader, obj, ver) where a transaction read an object that it had written and didn't see its own last write, or read a version
    that it wrote only later. Reads come in the order of op_seq."""
    mine = W.partitionBy("txn_id", "obj").orderBy("op_seq", "kind")
    before = F.last(F.when(F.col("kind") == "w", F.col("ver")), ignorenulls=True).over(mine.rowsBetween(W.unboundedPreceding, -1))
    later = F.max(F.when(F.col("kind") == "w", F.lit(True))).over(W.partitionBy("txn_id", "obj", "ver"))
    seen = h.ops.filter("ver IS NOT NULL").withColumn("own", before).withColumn("later", later)
    bad = seen.filter("kind <> 'w'").filter((F.col("own") != F.col("ver")) | (F.col("own").isNull() & F.coalesce("later", F.lit(False))))
    return bad.select("txn_id", "obj", "ver").distinct().join(committed(h).select("txn_id"), "txn_id").select(F.col("txn_id").alias("reader"), "obj", "ver")


def duplicate_versions(h: History) -> DataFrame:
    """(obj, ver, n) written more than once."""
    return h.ops.filter("kind = 'w'").groupBy("obj", "ver").agg(F.count("*").alias("n")).filter("n > 1")


def findings(h: History, predicates: bool = True) -> DataFrame:
    """(reason, reader, obj, ver): every read that no serial order explains."""
    tell = lambda df, why: df.select(F.lit(why).alias("reason"), "reader", "obj", "ver")
    out = tell(aborted_reads(h), "aborted_read").unionAll(tell(intermediate_reads(h), "intermediate_read")).unionAll(tell(orphan_reads(h), "orphan_read")).unionAll(tell(own_reads(h), "own_read"))
    if predicates and h.preds is not None:
        out = out.unionAll(tell(own_theta_reads(h), "own_predicate")).unionAll(tell(false_returns(h), "false_return"))
    return out


def domain(obj) -> F.col:
    return F.split_part(obj, F.lit(":"), F.lit(1))


def _meets() -> Column:
    """Whether a version (v1, v2, deleted) meets a predicate (col, lo, hi)."""
    value = F.when(F.col("col") == "v1", F.col("v1")).otherwise(F.col("v2"))
    return F.coalesce(~F.col("deleted") & value.between(F.col("lo"), F.col("hi")), F.lit(False))


def theta(h: History) -> DataFrame:
    """(pred_id, obj, ver, holds) for every predicate and version of its domain; a deleted version meets none. As many rows as pairs;
    the verifier uses matches() and truth() instead."""
    of = h.preds.join(h.vers.withColumn("domain", domain(F.col("obj"))), "domain")
    return of.select("pred_id", "obj", "ver", _meets().alias("holds"))


#: Rows of versions, dealt to buckets, up to which they go to every executor: few ranges would leave few and uneven tasks else.
BROADCAST_ROWS = 2_000_000
#: Pairs of a predicate and a version that a task stands for.
TASK_PAIRS = 5_000_000


def ranged(preds: DataFrame, held: DataFrame, keys: list[str]) -> DataFrame:
    """preds (pred_id, col, lo, hi, *keys, ...) joined with held (v1, v2, *keys, ...) whose value in the column lies in the range.

    A range is dealt to the two buckets at most that it touches, of a width between one and two times its own, and a version to its
    bucket of each width that occurs: the join grows with the matches and not with predicates times versions. Predicates are dealt to
    as many tasks as their work asks for, by pred_id.
    """
    level = F.greatest(F.lit(-20), F.ceil(F.log2(F.col("hi") - F.col("lo")))).cast("int")
    preds = preds.filter("lo <= hi").withColumn("level", F.when(F.col("hi") > F.col("lo"), level).otherwise(F.lit(-20)))
    levels = {r.level: r["count"] for r in preds.groupBy("level").count().collect()}  # powers of two: a hundred or so at most
    at = lambda x: F.floor(x / F.pow(F.lit(2.0), F.col("level"))).cast("long")
    n = held.count()
    tasks = min(512, sum(levels.values()) * n // TASK_PAIRS)
    asked = preds.repartition(tasks, "pred_id") if tasks > 1 else preds
    asked = asked.withColumn("bucket", F.explode(F.sequence(at(F.col("lo")), at(F.col("hi")))))
    value = F.stack(F.lit(2), F.lit("v1"), F.col("v1"), F.lit("v2"), F.col("v2")).alias("col", "value")
    held = held.select(*(c for c in held.columns if c not in ("v1", "v2")), value).filter("value IS NOT NULL AND NOT isnan(value)")
    held = held.withColumn("level", F.explode(F.lit([*levels]).cast("array<int>"))).withColumn("bucket", at(F.col("value")))
    if 2 * n * len(levels) <= BROADCAST_ROWS:
        held = F.broadcast(held)
    return asked.join(held, [*keys, "col", "level", "bucket"]).filter(F.col("value").between(F.col("lo"), F.col("hi")))


def matches(h: History) -> DataFrame:
    """(pred_id, obj, ver) for versions that meet a predicate."""
    held = h.vers.filter("NOT deleted").select(domain(F.col("obj")).alias("domain"), "obj", "ver", "v1", "v2")
    return ranged(h.preds, held, ["domain"]).select("pred_id", "obj", "ver")


def theta_counts(h: History) -> DataFrame:
    """(pred_id, versions, matching): the rows of theta() and those that hold, counted without making the pairs."""
    from orderproof.operators import dense

    sizes = h.vers.groupBy(domain(F.col("obj")).alias("domain")).agg(F.count("*").alias("n"))
    every = h.preds.join(F.broadcast(sizes), "domain").groupBy("pred_id").agg(F.sum("n").alias("versions"))
    met = dense.match_sums(h, ("matching",))
    return every.join(met, "pred_id", "left").select("pred_id", "versions", F.coalesce("matching", F.lit(0)).alias("matching"))


def theta_read_counts(h: History) -> DataFrame:
    """(txn_id, pred_id, objects, known): the rows of theta_reads() and those of known versions, counted without making the objects
    that weren't returned."""
    from orderproof.operators import dense

    return dense.returned_counts(h).select("txn_id", "pred_id", (F.col("every") - F.col("met") + F.col("known")).alias("objects"), "known")


def unknown_theta_counts(h: History) -> DataFrame:
    """(txn_id, pred_id, objects): the rows of unknown_theta_reads() by read, counted without making them."""
    from orderproof.operators import dense

    return dense.returned_counts(h, own=True).select("txn_id", "pred_id", (F.col("every") - F.col("met")).alias("objects")).filter("objects > 0")


def truth(h: History, pairs: DataFrame) -> DataFrame:
    """(pred_id, obj, ver, holds) for all versions of the given pairs (pred_id, obj)."""
    return pairs.join(h.vers, "obj").join(h.preds, "pred_id").select("pred_id", "obj", "ver", _meets().alias("holds"))


def asked(h: History) -> DataFrame:
    """(txn_id, pred_id, at): each predicate read and its place; a pred_id stands for one read of a transaction."""
    return h.ops.filter("kind = 'pr'").groupBy("txn_id", "pred_id").agg(F.min("op_seq").alias("at"))


def own_theta(h: History) -> DataFrame:
    """(txn_id, pred_id, obj, ver): predicate reads of objects that the reader had written before: they see its last write."""
    mine = h.ops.filter("kind = 'w'").select("txn_id", "obj", "ver", "op_seq").join(asked(h), "txn_id").filter("op_seq < at")
    return mine.groupBy("txn_id", "pred_id", "obj").agg(F.max_by("ver", "op_seq").alias("ver"))


def own_theta_reads(h: History) -> DataFrame:
    """(reader, obj, ver) where a predicate read left out the reader's own write although it matches."""
    known = h.ops.filter("kind = 'pr' AND ver IS NOT NULL").select("txn_id", "pred_id", "obj")
    own = own_theta(h).join(known, ["txn_id", "pred_id", "obj"], "left_anti").join(committed(h).select("txn_id"), "txn_id")
    of = own.join(h.vers.select("obj", "ver", "v1", "v2", "deleted"), ["obj", "ver"]).join(h.preds.withColumnRenamed("domain", "of"), "pred_id").filter(domain(F.col("obj")) == F.col("of"))
    return of.filter(_meets()).select(F.col("txn_id").alias("reader"), "obj", "ver").distinct()


def false_returns(h: History) -> DataFrame:
    """(reader, obj, ver) where a predicate read returned a version that doesn't match."""
    known = h.ops.filter("kind = 'pr' AND ver IS NOT NULL").select("txn_id", "pred_id", "obj", "ver").join(committed(h).select("txn_id"), "txn_id")
    of = known.join(h.vers.select("obj", "ver", "v1", "v2", "deleted"), ["obj", "ver"]).join(h.preds, "pred_id")
    return of.filter(~_meets()).select(F.col("txn_id").alias("reader"), "obj", "ver").distinct()


def theta_reads(h: History) -> DataFrame:
    """(txn_id, pred_id, obj, ver): each predicate read over all objects of its domain; ver is null where no match was returned."""
    objects = h.vers.select("obj", domain(F.col("obj")).alias("domain")).distinct()
    every = asked(h).join(h.preds.select("pred_id", "domain"), "pred_id").join(objects, "domain").select("txn_id", "pred_id", "obj")
    known = h.ops.filter("kind = 'pr' AND ver IS NOT NULL").select("txn_id", "pred_id", "obj", "ver")
    return every.join(known, ["txn_id", "pred_id", "obj"], "left")


def unknown_theta_reads(h: History) -> DataFrame:
    """Predicate reads of objects whose seen version isn't known."""
    own = own_theta(h).select("txn_id", "pred_id", "obj")
    unknown = theta_reads(h).filter("ver IS NULL").join(own, ["txn_id", "pred_id", "obj"], "left_anti")
    return unknown.join(committed(h).select("txn_id", "s", "e"), "txn_id").drop("ver")


def open_theta_reads(h: History) -> DataFrame:
    """Those unknown predicate reads that mean anything, as unknown_theta_reads() gives them: of objects some version of which
    matches. Any version explains the others."""
    pairs = matches(h).select("pred_id", "obj").distinct()
    every = asked(h).select("txn_id", "pred_id").join(pairs, "pred_id")
    keys = ["txn_id", "pred_id", "obj"]
    known = h.ops.filter("kind = 'pr' AND ver IS NOT NULL").select(*keys).unionAll(own_theta(h).select(*keys))
    return every.join(known, keys, "left_anti").join(committed(h).select("txn_id", "s", "e"), "txn_id").select("txn_id", "pred_id", "obj", "s", "e")


def lowered(h: History, writes_by: DataFrame) -> History:
    """h with predicate writes as writes of the rows they changed. writes_by: (txn_id, op_seq, pred_id, obj, ver) says which rows a
    predicate operation of that place changed and which versions it left; it also reads them, as the predicate read it is."""
    ops = writes_by.select("txn_id", F.col("op_seq").cast("int"), F.lit("w").alias("kind"), "obj", "ver", F.lit(None).cast("int").alias("pred_id"), F.lit(None).cast("long").alias("op_s"), F.lit(None).cast("long").alias("op_e"))
    return h.but(ops=h.ops.unionByName(ops))
