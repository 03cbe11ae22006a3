"""Complete histories: those that say of every read which version it saw, and in which order versions came."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.functions.closure import schedule
from orderproof.operators import deps, prelim
from orderproof.plans import islands
from orderproof.plans.global_order import ranked
from orderproof.schema import History
from orderproof.sources.scratch import written


def differences(complete: History, observed: History) -> DataFrame:
    """(txn_id, op_seq, obj, complete_ver, observed_ver): operations that only one history has, or of which the observed one knows
    another version. An unknown version in the observed history is compatible with any. No rows: the histories are compatible."""
    keys = ["txn_id", "op_seq", "kind", "obj"]
    side = lambda h, name: h.ops.select(*keys, F.col("ver").alias(name), F.lit(True).alias(f"in_{name}"))
    a, b = side(complete, "complete_ver").alias("a"), side(observed, "observed_ver").alias("b")
    same = [F.col(f"a.{k}").eqNullSafe(F.col(f"b.{k}")) for k in keys]
    met = a.join(b, same[0] & same[1] & same[2] & same[3], "full_outer")
    other = F.col("in_complete_ver").isNull() | F.col("in_observed_ver").isNull() | (F.col("observed_ver").isNotNull() & ~F.col("observed_ver").eqNullSafe(F.col("complete_ver")))
    return met.filter(other).select(F.coalesce("a.txn_id", "b.txn_id").alias("txn_id"), F.coalesce("a.op_seq", "b.op_seq").alias("op_seq"), F.coalesce("a.obj", "b.obj").alias("obj"), "complete_ver", "observed_ver")


def cyclic_stretches(places: DataFrame, edges: DataFrame, timed: bool = False) -> DataFrame:
    """(stretch, txns, cycle): the stretches of places (txn_id, idx) that edges (src, dst) make cyclic, with one cycle each.

    Edges that point forward can't make a cycle by themselves, so the places are cut wherever no backward edge spans a gap; only
    stretches with such an edge go to workers. timed: places, in the order of ends, have s and e, and client times are edges too; these
    point forward, and several in a row are one, so those between the ends of edges are enough.
    """
    inside = _stretches(places, edges)
    if timed:
        side = lambda c: places.select(F.col("txn_id").alias(c), F.col("s").alias(f"{c}_s"), F.col("e").alias(f"{c}_e"))
        inside = inside.join(side("src"), "src").join(side("dst"), "dst")

    def peel(key, pdf: pd.DataFrame) -> pd.DataFrame:
        ids = sorted({*pdf.src, *pdf.dst})
        at = {x: i for i, x in enumerate(ids)}
        s, e = [0] * len(ids), [1] * len(ids)  # one interval for all: edges alone count
        if timed:
            for c in ("src", "dst"):
                for x, begin, end in zip(pdf[c], pdf[f"{c}_s"], pdf[f"{c}_e"], strict=True):
                    s[at[x]], e[at[x]] = int(begin), int(end)
        cycle = schedule(s, e, [(at[u], at[v]) for u, v in zip(pdf.src, pdf.dst, strict=True)])[1]
        return pd.DataFrame([(int(key[0]), len(ids), [int(ids[u]) for u, _, _ in cycle])] if cycle else [], columns=["stretch", "txns", "cycle"])

    return inside.groupBy("src_in").applyInPandas(peel, "stretch long, txns long, cycle array<long>")


def strong_components(places: DataFrame, edges: DataFrame) -> DataFrame:
    """(txn_id, component): transactions that reach each other, by their smallest id; those alone in theirs aren't told."""

    def connect(key, pdf: pd.DataFrame) -> pd.DataFrame:
        out, back = {}, {}
        for u, v in zip(pdf.src, pdf.dst, strict=True):
            out.setdefault(u, []).append(v)
            back.setdefault(v, []).append(u)

        def walk(start, of, seen):
            todo, ended = [(start, iter(of.get(start, ())))], []
            seen.add(start)
            while todo:
                x, rest = todo[-1]
                y = next((y for y in rest if y not in seen), None)
                if y is None:
                    ended.append(todo.pop()[0])
                else:
                    seen.add(y)
                    todo.append((y, iter(of.get(y, ()))))
            return ended

        seen: set = set()
        last = [x for start in sorted(out) if start not in seen for x in walk(start, out, seen)]
        seen, rows = set(), []
        for x in reversed(last):
            if x not in seen:
                own = walk(x, back, seen)
                rows += [(int(y), int(min(own))) for y in own] if len(own) > 1 else []
        return pd.DataFrame(rows, columns=["txn_id", "component"])

    return _stretches(places, edges).groupBy("src_in").applyInPandas(connect, "txn_id long, component long")


def _stretches(places: DataFrame, edges: DataFrame) -> DataFrame:
    """(src_in, src, dst): edges within stretches that hold a backward one."""
    at = lambda df, c: df.join(places.select(F.col("txn_id").alias(c), F.col("idx").alias(f"{c}_at")), c)
    placed = written(at(at(edges.select("src", "dst").distinct(), "src"), "dst"))
    back = placed.filter("dst_at <= src_at").select(F.col("dst_at").alias("low"), F.col("src_at").alias("high"))
    cut = islands.assign(places, back).select("idx", "island")
    busy = back.join(cut, F.col("low") == F.col("idx")).select("island").distinct()
    side = lambda c: cut.select(F.col("idx").alias(f"{c}_at"), F.col("island").alias(f"{c}_in"))
    inside = placed.join(side("src"), "src_at").join(side("dst"), "dst_at").filter("src_in = dst_in").join(busy, F.col("src_in") == F.col("island"), "left_semi")
    return inside.select("src_in", "src", "dst")


def is_serializable(h: History, order: DataFrame, predicate_reads: DataFrame | None = None) -> DataFrame:
    """One row: whether a complete history is serializable, the bad reads and the cyclic stretches of its graph. order: (obj, ver, pos,
    txn_id); predicate_reads: (txn_id, pred_id, obj, ver) for all objects that some version of which matches."""
    edges = deps.dsg(h, order).select("src", "dst")
    if predicate_reads is not None:
        edges = edges.unionAll(deps.pred_deps(h, order, predicate_reads).select("src", "dst"))
    places = written(ranked(prelim.committed(h).select("txn_id", "e"), "e", ["txn_id"]))
    cycles = cyclic_stretches(places, edges).agg(F.count("*").alias("cyclic"))
    bad = prelim.findings(h).agg(F.count("*").alias("bad_reads"))
    return cycles.withColumn("one", F.lit(1)).join(bad.withColumn("one", F.lit(1)), "one").select(((F.col("cyclic") == 0) & (F.col("bad_reads") == 0)).alias("serializable"), "bad_reads", "cyclic")  # a row each


def chosen_graph(sets: DataFrame, chosen: DataFrame) -> DataFrame:
    """(src, dst): the edges that an assignment adds. sets: edges of both outcomes of pairs (i, j, side, src, dst); chosen: (i, j, side).
    A pair without a choice adds nothing."""
    return sets.join(chosen, ["i", "j", "side"], "left_semi").select("src", "dst").distinct()


def by_end(pairs: DataFrame, h: History) -> DataFrame:
    """The assignment that follows the ends of transactions, ties to the smaller id: (i, j, side)."""
    end = prelim.committed(h).select("txn_id", "e")
    met = pairs.select("i", "j").distinct().join(end.select(F.col("txn_id").alias("i"), F.col("e").alias("ei")), "i").join(end.select(F.col("txn_id").alias("j"), F.col("e").alias("ej")), "j")
    return met.select("i", "j", F.when((F.col("ei") < F.col("ej")) | ((F.col("ei") == F.col("ej")) & (F.col("i") < F.col("j"))), 0).otherwise(1).alias("side"))


def validation(h: History, order: DataFrame | None = None) -> DataFrame:
    """(reader, pred_id, obj, cand, before, after): given the order of versions, what each choice of an unseen version means: the latest
    flip at or before it (the first version where there is none) comes before the reader, and the reader before the next flip."""
    flips = deps.theta_flips(h, deps.version_order(h) if order is None else order)
    spans = W.partitionBy("pred_id", "obj").orderBy("pos")
    last = F.last(F.when(F.col("flips"), F.col("txn_id")), ignorenulls=True).over(spans.rowsBetween(W.unboundedPreceding, 0))
    nxt = F.first(F.when(F.col("flips"), F.col("txn_id")), ignorenulls=True).over(spans.rowsBetween(1, W.unboundedFollowing))
    first = F.first("txn_id").over(spans.rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    at = flips.withColumn("before", F.coalesce(last, first)).withColumn("after", nxt).filter("NOT holds")
    asked = prelim.open_theta_reads(h).select(F.col("txn_id").alias("reader"), "pred_id", "obj")
    return asked.join(at.select("pred_id", "obj", F.col("txn_id").alias("cand"), "before", "after"), ["pred_id", "obj"]).filter("cand <> reader").select("reader", "pred_id", "obj", "cand", "before", "after")


