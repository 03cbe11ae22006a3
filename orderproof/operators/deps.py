"""Dependency edges, always from the transaction that comes first to the one that comes after it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.operators import prelim
from orderproof.schema import INITIAL, History


def _edges(df: DataFrame, etype: str) -> DataFrame:
    return df.filter("src <> dst").select("src", "dst", F.lit(etype).alias("etype"), "obj").distinct()


def item_wr(h: History) -> DataFrame:
    """Writer of an installed version before its readers."""
    w = prelim.installed(h).select(F.col("txn_id").alias("src"), "obj", "ver")
    return _edges(prelim.reads(h).select(F.col("txn_id").alias("dst"), "obj", "ver").join(w, ["obj", "ver"]), "wr")


# -- complete histories: version_order has (obj, ver, pos, txn_id), pos from 1


def version_order(h: History) -> DataFrame:
    """The order of installed versions by their writers' end times, which is the true one of a serial run."""
    by = W.partitionBy("obj").orderBy("e", "txn_id")
    return prelim.installed(h).select("obj", "ver", F.row_number().over(by).alias("pos"), "txn_id")


def item_ww(order: DataFrame, direct: bool = True) -> DataFrame:
    """Overwritten before overwriter: the next version only, or all later ones (as many edges as pairs of writers)."""
    if direct:
        nxt = order.withColumn("dst", F.lead("txn_id").over(W.partitionBy("obj").orderBy("pos")))
        return _edges(nxt.filter("dst IS NOT NULL").withColumnRenamed("txn_id", "src"), "ww")
    a, b = order.select("obj", F.col("pos").alias("p"), F.col("txn_id").alias("src")), order.select("obj", F.col("pos").alias("q"), F.col("txn_id").alias("dst"))
    return _edges(a.join(b, "obj").filter("p < q"), "ww")


def item_rw(h: History, order: DataFrame, direct: bool = True) -> DataFrame:
    """Reader of a version before the writer of the next one, or of all later ones; readers of the initial version before the first."""
    r = prelim.reads(h).select(F.col("txn_id").alias("src"), "obj", "ver")
    at = order.select("obj", "ver", "pos")
    placed = r.join(at, ["obj", "ver"], "left").withColumn("pos", F.when(F.col("ver") == INITIAL, 0).otherwise(F.col("pos"))).filter("pos IS NOT NULL")
    later = order.select("obj", F.col("pos").alias("q"), F.col("txn_id").alias("dst"))
    if direct:
        return _edges(placed.withColumn("q", F.col("pos") + 1).join(later, ["obj", "q"]), "rw")
    return _edges(placed.join(later, "obj").filter("q > pos"), "rw")


def dsg(h: History, order: DataFrame) -> DataFrame:
    """Direct serialization graph of a complete history without predicates."""
    return item_wr(h).unionByName(item_ww(order)).unionByName(item_rw(h, order))


def theta_flips(h: History, order: DataFrame) -> DataFrame:
    """(pred_id, obj, ver, pos, txn_id, holds, flips): whether each version changes the truth of each predicate that some version of the
    object meets. The initial version, where there is one, is at place 0; nothing meets a predicate before the first version."""
    t = prelim.truth(h, prelim.matches(h).select("pred_id", "obj").distinct())
    first = h.vers.filter(F.col("ver") == INITIAL).select("obj", "ver", F.lit(0).alias("pos"), F.lit(INITIAL).cast("long").alias("txn_id"))
    placed = order.select("obj", "ver", "pos", "txn_id").unionByName(first).join(t, ["obj", "ver"])
    was = F.coalesce(F.lag("holds").over(W.partitionBy("pred_id", "obj").orderBy("pos")), F.lit(False))
    return placed.withColumn("flips", F.col("holds") != was)


def serial_theta_reads(h: History) -> DataFrame:
    """(txn_id, pred_id, obj, ver): the version that each predicate read sees if transactions ran in the order of their end times, of
    objects some version of which matches: with these a history is complete."""
    from orderproof.plans.global_order import running_all

    pairs = prelim.matches(h).select("pred_id", "obj").distinct()
    asks = prelim.asked(h).join(prelim.committed(h).select("txn_id", "e"), "txn_id").join(pairs, "pred_id")
    none = F.lit(None).cast("struct<e:long,txn_id:long,ver:long>")
    points = asks.select("obj", "e", "txn_id", "pred_id", none.alias("w"))
    points = points.unionByName(prelim.installed(h).select("obj", "e", "txn_id", F.lit(None).cast("int").alias("pred_id"), F.struct("e", "txn_id", "ver").alias("w")))
    # a read stands before its own transaction's writes
    seen = running_all(points.withColumn("o", F.col("w").isNotNull().cast("int")), "e", ["txn_id", "o"], {"last": ("max", F.col("w"), True)}, ["obj"])
    return seen.filter("o = 0").select("txn_id", "pred_id", "obj", F.coalesce("last.ver", F.lit(INITIAL)).cast("long").alias("ver"))


def pred_deps(h: History, order: DataFrame | None = None, reads: DataFrame | None = None) -> DataFrame:
    """Predicate read- and anti-dependencies of a complete history: the latest flip at or before the version read precedes the
    reader, and the reader precedes the earliest flip after it. By default the history is completed in the order of end times."""
    flips = theta_flips(h, version_order(h) if order is None else order)
    spans = W.partitionBy("pred_id", "obj").orderBy("pos")
    last = F.last(F.when(F.col("flips"), F.col("txn_id")), ignorenulls=True).over(spans.rowsBetween(W.unboundedPreceding, 0))
    nxt = F.first(F.when(F.col("flips"), F.col("txn_id")), ignorenulls=True).over(spans.rowsBetween(1, W.unboundedFollowing))
    first = F.first("txn_id").over(spans.rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    at = flips.select("pred_id", "obj", "ver", F.coalesce(last, first).alias("before"), nxt.alias("after"))
    r = (serial_theta_reads(h) if reads is None else reads).join(at, ["pred_id", "obj", "ver"])
    wr = _edges(r.filter(F.col("before") != INITIAL).select(F.col("before").alias("src"), F.col("txn_id").alias("dst"), "obj"), "pwr")
    rw = _edges(r.filter("after IS NOT NULL").select(F.col("txn_id").alias("src"), F.col("after").alias("dst"), "obj"), "prw")
    return wr.unionByName(rw)


# -- client times: a transaction that ended no later than another began comes first


def time_edge_count(h: History) -> DataFrame:
    """Number of time edges, without making them: for each start, the ends at or before it."""
    t = prelim.committed(h)
    points = t.select(F.col("e").alias("at"), F.lit(0).alias("kind")).unionAll(t.select(F.col("s").alias("at"), F.lit(1).alias("kind")))
    from orderproof.plans.global_order import running

    counted = running(points, "at", ["kind"], F.when(F.col("kind") == 0, 1).otherwise(0), "sum", "ended")
    return counted.filter("kind = 1").agg(F.coalesce(F.sum("ended"), F.lit(0)).cast("long").alias("n"))


def first_wave(at: str, rows: DataFrame, later: DataFrame, keys: list[str]) -> DataFrame:
    """For each row the later transactions on the same keys that begin at or after `at` and before the earliest end of any of
    these: what begins after that follows from a time edge. later: keys, dst, ds, de.

    In start order these are consecutive places. One sorted pass counts the places before each row and takes the earliest end
    behind it, a second one counts the places before that end; the places are then made, as many as there are edges.
    """
    from orderproof.plans.global_order import running_all
    from orderproof.sources.scratch import written

    mark = F.col("row").isNull()
    row = F.struct(*rows.columns)
    kind = rows.select(row.alias("row")).schema["row"].dataType
    marks = later.select(*keys, F.col("ds").alias("x"), F.lit(1).alias("o"), "dst", "de", F.lit(None).cast(kind).alias("row"))
    points = rows.select(*keys, F.col(at).alias("x"), F.lit(0).alias("o"), F.lit(None).cast("long").alias("dst"), F.lit(None).cast("long").alias("de"), row.alias("row"))
    one = F.when(mark, 1).otherwise(0)
    # a row stands before marks of the same time: those count as later ones
    passed = written(running_all(points.unionByName(marks), "x", ["o", "dst"], {"upto": ("sum", one, True), "bound": ("min", F.col("de"), False)}, keys))
    places = passed.filter(mark).select(*keys, (F.col("upto") - 1).alias("place"), "dst", F.col("x").alias("ds"), "de")
    open_ = passed.filter(~mark & F.col("bound").isNotNull()).select(*keys, F.col("bound").alias("x"), F.lit(0).alias("o"), F.col("upto").alias("first"), "row")
    ends = open_.unionByName(marks.select(*keys, "x", "o", "row"), allowMissingColumns=True)
    upto = running_all(ends, "x", ["o"], {"stop": ("sum", one, True)}, keys).filter(~mark)
    made = upto.filter("stop > first").select(*keys, "row", F.explode(F.sequence("first", F.col("stop") - 1)).alias("place"))
    return made.join(places, [*keys, "place"]).select("row.*", "dst", "ds", "de")


def time_edges(h: History) -> DataFrame:
    """First-wave time edges; their closure is all of them. Found by rank, so no range join is needed."""
    from orderproof.plans.bounds import bounds

    every = bounds(h)
    ahead = every.filter("wave >= r + 1").select(F.col("txn_id").alias("src"), F.explode(F.sequence(F.col("r") + 1, F.col("wave"))).alias("j"))
    return ahead.join(every.select(F.col("idx").alias("j"), F.col("txn_id").alias("dst")), "j").select("src", "dst")


def rw_from_wr(h: History) -> DataFrame:
    """Reader of a version before each writer of the object that began after the version's writer had ended; first wave."""
    w = prelim.installed(h)
    r = prelim.reads(h).select(F.col("txn_id").alias("src"), "obj", "ver").join(w.select("obj", "ver", F.col("e").alias("we")), ["obj", "ver"])
    initial = prelim.reads(h).filter(F.col("ver") == INITIAL).select(F.col("txn_id").alias("src"), "obj", "ver", F.lit(-(1 << 62)).alias("we"))
    later = w.select("obj", F.col("txn_id").alias("dst"), F.col("s").alias("ds"), F.col("e").alias("de"))
    return _edges(first_wave("we", r.unionByName(initial), later, ["obj"]), "rw")


def known(h: History, timed: bool = True) -> DataFrame:
    """Edges of the known graph besides time edges, which stay implicit: wr, and with client times rw after determined ww."""
    return item_wr(h).unionByName(rw_from_wr(h)) if timed else item_wr(h)


def time_contradictions(h: History, edges: DataFrame) -> DataFrame:
    """Edges whose later end had ended before the earlier one began: each refutes the history."""
    t = prelim.committed(h)
    a, b = t.select(F.col("txn_id").alias("src"), F.col("s").alias("src_s")), t.select(F.col("txn_id").alias("dst"), F.col("e").alias("dst_e"))
    return edges.join(a, "src").join(b, "dst").filter("dst_e <= src_s").select(*edges.columns)
