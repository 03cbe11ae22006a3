"""Either-or constraints on what is not certain: who overwrote whom, and which version a predicate read skipped."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderproof.operators import dense, prelim
from orderproof.schema import INITIAL, History


def item_pair_counts(h: History) -> DataFrame:
    """Per object the writers and their pairs, counted and not made."""
    n = prelim.installed(h).groupBy("obj").agg(F.countDistinct("txn_id").alias("writers"))
    return n.withColumn("pairs", (F.col("writers") * (F.col("writers") - 1) / 2).cast("long"))


def overlapping(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Pairs i < j of rows (txn_id, s, e, *keys) with equal keys and overlapping intervals, as (*keys, i, j).

    An interval belongs to the class of its length, a power of two, and touches two buckets of that width at most. It is dealt to
    these, and as the shorter side of a pair to the buckets of each wider class that occurs. A pair meets in the class of its longer
    interval and is kept in the first bucket both lie in. So a row is in a bounded number of buckets however long it is, and the join
    grows with the overlap and not with the square of a key's rows.
    """
    rows = rows.withColumn("level", F.ceil(F.log2(F.greatest(F.col("e") - F.col("s"), F.lit(1)))).cast("int"))
    levels = [r.level for r in rows.select("level").distinct().collect()]  # 63 at most
    at = lambda c, w: F.call_function("shiftright", F.col(c) if isinstance(c, str) else c, F.col(w))
    put = lambda df, w: df.withColumn("bucket", F.explode(F.sequence(at("s", w), at(F.col("e") - 1, w))))
    side = lambda df, x: df.select(*keys, "bucket", "wide", F.col("txn_id").alias(x), *(F.col(c).alias(f"{x}_{c}") for c in ("s", "e", "level")))
    a = side(put(rows.withColumn("wide", F.col("level")), "wide"), "a")
    b = side(put(rows.withColumn("wide", F.explode(F.filter(F.lit(levels).cast("array<int>"), lambda x: x >= F.col("level")))), "wide"), "b")
    met = a.join(b, [*keys, "wide", "bucket"]).filter("a_s < b_e AND b_s < a_e AND (b_level < wide OR a < b)")
    met = met.filter(F.col("bucket") == F.call_function("shiftright", F.greatest("a_s", "b_s"), F.col("wide")))
    return met.select(*keys, F.least("a", "b").alias("i"), F.greatest("a", "b").alias("j"))


def item_pairs(h: History, timed: bool = True) -> DataFrame:
    """(obj, i, j): pairs of writers whose order is open; with client times only overlapping ones."""
    w = prelim.installed(h).select("txn_id", "obj", "s", "e")
    if timed:
        return overlapping(w, ["obj"])
    return w.select("obj", F.col("txn_id").alias("i")).join(w.select("obj", F.col("txn_id").alias("j")), "obj").filter("i < j")


def item_edge_sets(h: History, pairs: DataFrame) -> DataFrame:
    """(obj, i, j, side, src, dst): the edges of both outcomes; side 0 has i before j and i's readers before j, side 1 the mirror."""
    w = prelim.installed(h).select("txn_id", "obj", "ver")
    readers = prelim.reads(h).select(F.col("txn_id").alias("reader"), "obj", "ver").join(w, ["obj", "ver"]).select("obj", F.col("txn_id").alias("of"), "reader")
    both = pairs.select("obj", "i", "j", F.lit(0).alias("side"), F.col("i").alias("of"), F.col("j").alias("dst")).unionAll(
        pairs.select("obj", "i", "j", F.lit(1).alias("side"), F.col("j").alias("of"), F.col("i").alias("dst"))
    )
    ww = both.select("obj", "i", "j", "side", F.col("of").alias("src"), "dst")
    rw = both.join(readers, ["obj", "of"]).filter("reader <> dst").select("obj", "i", "j", "side", F.col("reader").alias("src"), "dst")
    return ww.unionAll(rw).distinct()


def coalesced(sets: DataFrame) -> DataFrame:
    """Edge sets of one pair over all objects as one constraint (cid): mixed directions would be a cycle of two anyway."""
    return sets.select(F.concat_ws("-", "i", "j").alias("cid"), "i", "j", "side", "src", "dst").distinct()


def predicate(h: History, unknown: DataFrame | None = None) -> DataFrame:
    """(cid, reader, obj, cand, src, dst, via_src, via_dst): one constraint for each predicate read that skipped an unknown version
    of an object. A candidate is a writer of a version that doesn't match (0: the initial one), which comes before the reader;
    the reader comes before each other writer of a matching version that overwrote the candidate's (via: only if that is so). The
    reader's own version is none of these: where it wrote before the read nothing is unknown, and later writes weren't there.
    unknown: the reads to take, as unmet() gives them; by default all whose object some version of which matches.
    """
    unknown = prelim.open_theta_reads(h) if unknown is None else unknown
    t = prelim.truth(h, unknown.select("pred_id", "obj").distinct())
    w = prelim.installed(h).join(t, ["obj", "ver"]).select("obj", "pred_id", "txn_id", "holds")
    initial = t.filter(F.col("ver") == INITIAL).select("obj", "pred_id", F.lit(INITIAL).cast("long").alias("txn_id"), "holds")
    w = w.unionByName(initial)
    unknown = unknown.select(F.col("txn_id").alias("reader"), "pred_id", "obj")
    cid = F.concat_ws("/", F.col("reader"), F.col("pred_id"), F.col("obj")).alias("cid")
    false = unknown.join(w.filter("NOT holds").select("obj", "pred_id", F.col("txn_id").alias("cand")), ["obj", "pred_id"]).filter("cand <> reader")
    true = w.filter(F.col("holds") & (F.col("txn_id") != INITIAL)).select("obj", "pred_id", F.col("txn_id").alias("m"))
    none = F.lit(None).cast("long")
    known = false.select(cid, "reader", "obj", "cand", F.col("cand").alias("src"), F.col("reader").alias("dst"), none.alias("via_src"), none.alias("via_dst"))
    open_ = false.join(true, ["obj", "pred_id"]).filter("m <> cand AND m <> reader").select(cid, "reader", "obj", "cand", F.col("reader").alias("src"), F.col("m").alias("dst"), F.col("cand").alias("via_src"), F.col("m").alias("via_dst"))
    return known.unionAll(open_)


def unmet(h: History) -> DataFrame:
    """Unknown predicate reads that client times alone don't meet, as prelim.unknown_theta_reads(h) gives them.

    A read is met by a candidate that ended before it if no match that began before the read's end also ended after the candidate's
    start. Told object by object, without a row for each read that is met.
    """
    return dense.unmet(h)


def empty_domains(h: History, candidates: DataFrame, unknown: DataFrame | None = None) -> DataFrame:
    """Unknown reads of objects of which no version fails the predicate: the history can't be serialised."""
    unknown = prelim.open_theta_reads(h) if unknown is None else unknown
    cid = F.concat_ws("/", F.col("txn_id"), F.col("pred_id"), F.col("obj"))
    return unknown.withColumn("cid", cid).join(candidates.select("cid").distinct(), "cid", "left_anti")


def avoided_literally(h: History, candidates: DataFrame) -> DataFrame:
    """Avoidance as published, for comparison only: every edge whose ends don't overlap goes, and candidates without edges with it. It
    isn't sound: an edge against time is a veto, and a candidate whose edges all follow from time is free and not impossible."""
    t = prelim.committed(h).select("txn_id", "s", "e")
    side = lambda c: t.select(F.col("txn_id").alias(c), F.col("s").alias(f"{c}_s"), F.col("e").alias(f"{c}_e"))
    return candidates.join(side("src"), "src").join(side("dst"), "dst").filter("src_s < dst_e AND dst_s < src_e").select(*candidates.columns).distinct()


def avoided(h: History, candidates: DataFrame) -> DataFrame:
    """Candidates after client times: one whose read edge time contradicts goes with all its edges; an open edge goes where time
    implies it or contradicts its via pair; where a candidate has nothing left the constraint is met, and goes as a whole. Where time
    contradicts every candidate the read edges stay, for no order meets the constraint."""
    t = prelim.committed(h).select("txn_id", "s", "e").unionAll(h.txns.sparkSession.createDataFrame([(INITIAL, -(1 << 62) - 1, -(1 << 62))], "txn_id long, s long, e long"))
    side = lambda c: t.select(F.col("txn_id").alias(c), F.col("s").alias(f"{c}_s"), F.col("e").alias(f"{c}_e"))
    x = candidates.join(side("src"), "src").join(side("dst"), "dst").join(side("via_src"), "via_src", "left").join(side("via_dst"), "via_dst", "left")
    implied, against = F.col("src_e") <= F.col("dst_s"), F.col("dst_e") <= F.col("src_s")
    x = x.withColumn("gone", F.col("via_src").isNull() & against).withColumn("moot", F.when(F.col("via_src").isNull(), implied).otherwise(implied | F.coalesce(F.col("via_dst_e") <= F.col("via_src_s"), F.lit(False))))
    each = x.groupBy("cid", "cand").agg(F.max("gone").alias("out"), F.min("moot").alias("free"))
    none = each.groupBy("cid").agg(F.min("out").alias("none")).filter("none").select("cid")
    left = each.filter("NOT out")
    met = left.groupBy("cid").agg(F.max("free").alias("met")).filter("NOT met").select("cid")
    kept = x.filter("NOT moot").join(left.filter("NOT free").select("cid", "cand"), ["cid", "cand"], "left_semi").join(met, "cid", "left_semi")
    return kept.select(*candidates.columns).unionByName(candidates.filter("via_src IS NULL").join(none, "cid", "left_semi").select(*candidates.columns))


def search_space(pairs: DataFrame) -> DataFrame:
    """log2 of the number of assignments: one bit a pair of writers."""
    return pairs.select("i", "j").distinct().agg(F.count("*").alias("log2_assignments"))
