"""Verification of a history: known edges and constraints by joins, cut into islands, each decided by a worker."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.functions.solver import solve
from orderproof.operators import complete, dense, deps, prelim
from orderproof.operators import constraints as cs
from orderproof.plans import islands
from orderproof.plans.bounds import bounds
from orderproof.plans.global_order import ranked, running_all
from orderproof.schema import INITIAL, History
from orderproof.sources.scratch import scope, written

ISLAND = "island long, txns long, ok boolean, reason string, constraints long, residual long, conflicts long, decisions long, cells long, first long, cycle array<struct<src:long,dst:long,kind:string>>, ord array<long>"
ROWS = "kind string, a long, b long, s long, e long, cid string, opt string, via_src long, via_dst long"


def constraint_rows(h: History, timed: bool, predicates: bool, avoid: str = "sound", overlap: bool = True) -> DataFrame:
    """(cid, opt, src, dst, via_src, via_dst): options of all constraints; an option without edges has a row with null ends.
    avoid: sound, none or literal (which may turn a verdict round); overlap: only pairs of writers that overlap in time."""
    sets = cs.coalesced(cs.item_edge_sets(h, cs.item_pairs(h, timed and overlap)))
    none = F.lit(None).cast("long")
    out = sets.select("cid", F.col("side").cast("string").alias("opt"), "src", "dst", none.alias("via_src"), none.alias("via_dst"))
    if predicates and h.preds is not None:
        unknown = written(cs.unmet(h) if timed and avoid == "sound" else prelim.open_theta_reads(h))
        p = every = cs.predicate(h, unknown)
        if timed and avoid != "none":
            every = written(every)
            p = cs.avoided(h, every) if avoid == "sound" else cs.avoided_literally(h, every)
        first = F.col("via_src") == INITIAL  # the initial version is overwritten by every other one
        keep = F.col("src") != INITIAL
        p = p.select(
            "cid", F.col("cand").cast("string").alias("opt"), F.when(keep, F.col("src")).alias("src"), F.when(keep, F.col("dst")).alias("dst"),
            F.when(~first, F.col("via_src")).alias("via_src"), F.when(~first, F.col("via_dst")).alias("via_dst"),
        )
        empty = cs.empty_domains(h, every, unknown).select("cid", F.lit("none").alias("opt"), F.col("txn_id").alias("src"), F.col("txn_id").alias("dst"), none.alias("via_src"), none.alias("via_dst"))
        out = out.unionByName(p.distinct()).unionByName(empty)
    return out


def known_edges(h: History, timed: bool) -> DataFrame:
    edges = deps.known(h, timed).select("src", "dst")
    if not timed:  # readers of initial versions come before all writers
        r = prelim.reads(h).filter(F.col("ver") == INITIAL).select(F.col("txn_id").alias("src"), "obj")
        edges = edges.unionAll(r.join(prelim.installed(h).select(F.col("txn_id").alias("dst"), "obj"), "obj").filter("src <> dst").select("src", "dst"))
    return edges.distinct()


def island_rows(h: History, timed: bool = True, predicates: bool = True, cut="back_edge", avoid: str = "sound", overlap: bool = True, made: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """The islands that time and known edges don't settle by themselves, as rows (island, *ROWS) of transactions, known edges and
    constraints. cut: back_edge, epoch, none, or what gives the bounds an island; made: known edges and constraint rows, where they are
    made already."""
    b = bounds(h)
    edges, rows = made or (written(known_edges(h, timed)), written(constraint_rows(h, timed, predicates, avoid, overlap)))
    place = b.select("txn_id", "idx")
    at = lambda df, c: df.join(place.select(F.col("txn_id").alias(c), F.col("idx").alias(f"{c}_at")), c, "left")
    placed = written(at(at(edges, "src"), "dst"))
    back = placed.filter("dst_at < src_at").select(F.col("dst_at").alias("low"), F.col("src_at").alias("high"))
    members = rows.select("cid", F.explode(F.array("src", "dst", "via_src", "via_dst")).alias("txn_id")).filter("txn_id IS NOT NULL").distinct().join(place, "txn_id")
    members = written(members)
    spans = members.groupBy("cid").agg(F.min("idx").alias("low"), F.max("idx").alias("high"))
    if callable(cut):
        cut_b = cut(b)
    elif cut == "none":
        cut_b = b.withColumn("island", F.lit(0).cast("long"))
    else:
        cover = back.unionAll(spans.select("low", "high"))
        if cut == "epoch":
            cover = cover.unionAll(b.select(F.col("idx").alias("low"), F.col("r").alias("high")))
        cut_b = islands.assign(b, cover)
    of = cut_b.select("txn_id", "island")
    busy = back.select(F.col("low").alias("idx")).unionAll(spans.select(F.col("low").alias("idx"))).distinct().join(cut_b.select("idx", "island"), "idx").select("island").distinct()
    t = cut_b.join(busy, "island", "left_semi")
    k = edges.join(of.withColumnRenamed("txn_id", "src"), "src").join(of.select(F.col("txn_id").alias("dst"), F.col("island").alias("other")), "dst").filter("island = other")
    k = k.join(busy, "island", "left_semi")
    home = members.join(of, "txn_id").groupBy("cid").agg(F.min("island").alias("island"))
    return _island_rows(t, k, rows.join(home, "cid"))


def end_islands(h: History, edges: DataFrame, rows: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """(places (txn_id, s, e, idx, island) in the order of ends, rows of the islands that this order doesn't settle, or None).

    Time edges point forward in the order of ends too. A constraint is settled if an option's edges all do, and so is what no backward
    edge and no unsettled constraint spans: a cycle through a gap needs an edge back over it. Settled constraints that lie in one such
    island are searched with the rest of it; of those that reach beyond, the edges that were taken are known edges inside. So islands
    that can be decided prove the history, but one that can't proves nothing if it holds such edges: by_island() decides then.
    """
    t = written(ranked(prelim.committed(h).select("txn_id", "s", "e"), "e", ["txn_id"]))
    place = t.select("txn_id", "idx")
    at = lambda df, c: df.join(place.select(F.col("txn_id").alias(c), F.col("idx").alias(f"{c}_at")), c, "left")
    back = written(at(at(edges, "src"), "dst").filter("dst_at <= src_at").select(F.col("dst_at").alias("low"), F.col("src_at").alias("high")))
    ahead = F.col("src").isNull() & (F.col("opt") != "none") | F.coalesce(F.col("src_at") < F.col("dst_at"), F.lit(False))
    options = at(at(rows.select("cid", "opt", "src", "dst"), "src"), "dst").groupBy("cid", "opt").agg(F.min(ahead).alias("ahead"))
    taken = written(options.groupBy("cid").agg(F.min(F.when(F.col("ahead"), F.col("opt"))).alias("took")))
    members = lambda df: df.select("cid", F.explode(F.array("src", "dst", "via_src", "via_dst")).alias("txn_id")).filter("txn_id IS NOT NULL").distinct()
    hard = rows.join(taken.filter("took IS NULL"), "cid", "left_semi")
    cover = written(back.unionAll(members(hard).join(place, "txn_id").groupBy("cid").agg(F.min("idx").alias("low"), F.max("idx").alias("high")).select("low", "high")))
    if not cover.limit(1).count():
        return t.withColumn("island", F.col("idx")), None
    cut = islands.assign(t, cover)
    busy = written(cover.select(F.col("low").alias("idx")).distinct().join(cut.select("idx", "island"), "idx").select("island").distinct())
    of = written(cut.join(busy, "island", "left_semi").select("txn_id", "island", "s", "e"))
    home = of.select("txn_id", "island")
    near = written(rows.join(members(rows).join(home, "txn_id").select("cid").distinct(), "cid", "left_semi"))
    lies = members(near).join(home, "txn_id", "left").groupBy("cid").agg(F.min("island").alias("island"), F.max("island").alias("other"), F.max(F.col("island").isNull()).alias("beyond"))
    lies = written(lies.withColumn("inside", (F.col("island") == F.col("other")) & ~F.col("beyond")))
    crossing = near.join(lies.filter("NOT inside"), "cid", "left_semi").join(taken, "cid").filter("opt = took AND src IS NOT NULL").select("src", "dst")
    sure = edges.unionAll(crossing).distinct()
    k = sure.join(home.withColumnRenamed("txn_id", "src"), "src").join(home.select(F.col("txn_id").alias("dst"), F.col("island").alias("other")), "dst").filter("island = other")
    c = near.join(lies.filter("inside").select("cid", "island"), "cid")
    return cut, _island_rows(of, k, c)


def _island_rows(t: DataFrame, k: DataFrame, c: DataFrame) -> DataFrame:
    """Rows (island, *ROWS) of transactions, known edges and constraints with their islands."""
    null = lambda *names: [F.lit(None).cast("string" if n in ("cid", "opt") else "long").alias(n) for n in names]
    t = t.select("island", F.lit("t").alias("kind"), F.col("txn_id").alias("a"), *null("b"), "s", "e", *null("cid", "opt", "via_src", "via_dst"))
    k = k.select("island", F.lit("k").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), *null("s", "e", "cid", "opt", "via_src", "via_dst"))
    c = c.select("island", F.lit("c").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), *null("s", "e"), "cid", "opt", "via_src", "via_dst")
    return t.unionAll(k).unionAll(c)


def _island(pdf: pd.DataFrame) -> tuple[list[int], list[int], list[int], list, list]:
    """(ids by start, starts, ends, known edges, constraints) of an island's rows."""
    t = pdf[pdf.kind == "t"].sort_values(["s", "a"])
    ids = [int(x) for x in t.a]
    at = {x: i for i, x in enumerate(ids)}
    known = [(at[int(x)], at[int(y)]) for x, y in zip(*(pdf.loc[pdf.kind == "k", c] for c in "ab"), strict=True)]
    options: dict[str, dict[str, list]] = {}
    for r in pdf[pdf.kind == "c"].itertuples():
        of = options.setdefault(r.cid, {})
        if r.opt == "none":  # nothing can be chosen
            continue
        edges = of.setdefault(r.opt, [])
        if pd.notna(r.a):
            via = (at[int(r.via_src)], at[int(r.via_dst)]) if pd.notna(r.via_src) else None
            edges.append((at[int(r.a)], at[int(r.b)], via))
    return ids, [int(x) for x in t.s], [int(x) for x in t.e], known, [list(o.values()) for _, o in sorted(options.items())]


def on_islands(h: History, work, kind: str, **cut) -> DataFrame:
    """work(starts, ends, known, constraints) -> rows on each island; kind: island, txns and what the rows have."""
    names = [x.split()[0] for x in kind.split(", ")]

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        ids, *island = _island(pdf)
        return pd.DataFrame([(int(key[0]), len(ids), *row) for row in work(*island)], columns=names)

    return island_rows(h, **cut).groupBy("island").applyInPandas(run, kind)


def by_island(h: History, timed: bool = True, predicates: bool = True, cut="back_edge", avoid: str = "sound", overlap: bool = True, made: tuple[DataFrame, DataFrame] | None = None, **search) -> DataFrame:
    """One row per island: what the worker found (see ISLAND). search: budget_s, time_first, prune and layout of solver.solve()."""
    return decided(island_rows(h, timed, predicates, cut, avoid, overlap, made), timed, **search)


def decided(rows: DataFrame, timed: bool = True, **search) -> DataFrame:
    """One row per island of the rows that island_rows() gives."""
    from orderproof.functions.closure import Band

    def decide(key, pdf: pd.DataFrame) -> pd.DataFrame:
        ids, s, e, known, cons = _island(pdf)
        out = solve(s, e, known, cons, timed, **search)
        sure = set(known)
        tell = lambda u, v, kind: "time" if kind == "time" else "known" if (u, v) in sure else "chosen"
        cycle = [{"src": ids[u], "dst": ids[v], "kind": tell(u, v, kind)} for u, v, kind in out.cycle]
        row = (int(key[0]), len(ids), out.ok, out.reason, len(cons), out.left, out.conflicts, out.decisions, Band(s, e, timed).cells(), ids[0], cycle, [ids[i] for i in out.order])
        return pd.DataFrame([row], columns=[x.split()[0] for x in ISLAND.split(", ")])

    return rows.groupBy("island").applyInPandas(decide, ISLAND)


def by_ends(h: History, made: tuple[DataFrame, DataFrame], **search) -> tuple[DataFrame, DataFrame | None, bool]:
    """(places, what was found an island, whether all are decided and hold) with islands cut in the order of ends, see end_islands()."""
    places, rows = end_islands(h, *made)
    if rows is None:
        return places, None, True
    found = written(decided(rows, **search))
    return places, found, not found.filter("ok IS NULL OR NOT ok").limit(1).count()


def ends_explain(h: History) -> bool:
    """Whether the item reads of installed and initial versions follow from the order of ends: each comes after the version's writer and
    before the next other writer of the object. Then choosing that order for every pair of writers makes all known and chosen edges
    point forward in it. A transaction's reads of its own version ask nothing."""
    return _follows(h, prelim.reads(h).select("obj", "ver", "txn_id", F.col("e").alias("at"), F.lit(0).alias("begin")))


def starts_explain(h: History) -> bool:
    """The same of the order that has writers at their ends and what only reads at its start, as snapshots are taken. Client times allow
    it: what ended no later than another began comes first, at equal times the end before the start."""
    wrote = prelim.installed(h).select("txn_id", F.lit(False).alias("only")).distinct()
    r = prelim.reads(h).join(wrote, "txn_id", "left").withColumn("only", F.coalesce("only", F.lit(True)))
    return _follows(h, r.select("obj", "ver", "txn_id", F.when(F.col("only"), F.col("s")).otherwise(F.col("e")).alias("at"), F.col("only").cast("int").alias("begin")))


def _follows(h: History, reads: DataFrame) -> bool:
    """Whether reads (obj, ver, txn_id, at, begin) see what writers installed in the order of ends; begin: 1 where `at` is a start."""
    by = W.partitionBy("obj").orderBy("e", "txn_id")
    end = F.struct(F.col("e").alias("at"), F.lit(0).alias("begin"), "txn_id")
    at = lambda n: F.lead(end, n).over(by)
    w = prelim.installed(h).select("obj", "ver", "e", "txn_id", at(1).alias("next"), at(2).alias("second"), (F.row_number().over(by) == 1).alias("first"))
    w = written(w)
    none = F.lit(None).cast("struct<at:long,begin:int,txn_id:long>")
    start = w.filter("first").select("obj", F.lit(INITIAL).cast("long").alias("ver"), none.alias("of"), end.alias("next"), F.col("next").alias("second"))
    spans = w.select("obj", "ver", end.alias("of"), "next", "second").unionByName(start)
    met = reads.select("obj", "ver", F.struct("at", "begin", "txn_id").alias("r")).join(spans, ["obj", "ver"]).filter(F.col("of").isNull() | (F.col("of.txn_id") != F.col("r.txn_id")))
    over = F.when(F.col("next.txn_id") == F.col("r.txn_id"), F.col("second")).otherwise(F.col("next"))
    early = F.coalesce(F.col("of") > F.col("r"), F.lit(False))
    return not met.filter(early | F.coalesce(over < F.col("r"), F.lit(False))).limit(1).count()


def explained(h: History) -> bool:
    """Whether an order that client times allow explains every read, item or predicate: no search is needed then, and all edges of the
    complete history with versions in the order of ends point forward in it. The order of ends is tried, and for histories without
    predicates that of starts_explain(). What History.returned holds is read as well."""
    if prelim.findings(h, False).limit(1).count():
        return False
    if ends_explain(h):
        return h.preds is None or dense.shown_by_ends(h)
    return h.preds is None and starts_explain(h)


def told_by_graph(h: History, edges: DataFrame) -> bool | None:
    """Whether item reads without findings are serializable, where the known edges and time hold a cycle (no) or the graph of the complete
    history with versions in the order of ends and time holds none (yes); None: neither, so a search must tell."""
    if deps.time_contradictions(h, edges).limit(1).count():
        return False
    places = written(ranked(prelim.committed(h).select("txn_id", "s", "e"), "e", ["txn_id"]))
    cyclic = lambda df: bool(complete.cyclic_stretches(places, df.select("src", "dst"), timed=True).limit(1).count())
    if cyclic(edges):
        return False
    return None if cyclic(deps.dsg(h, deps.version_order(h))) else True


def serializable(h: History, **search) -> DataFrame:
    """One row (serializable), as verdict() tells it; no constraint is made where explained() or told_by_graph() tell."""
    with scope(h.txns.sparkSession) as kept:
        one = lambda x: kept(h.txns.sparkSession.range(1).select(F.lit(x).alias("serializable")))
        h = h.but(txns=written(h.txns), ops=written(h.ops))
        if explained(h):
            return one(True)
        if h.preds is None:
            told = False if prelim.findings(h).limit(1).count() else told_by_graph(h, written(known_edges(h, True)))
            if told is not None:
                return one(told)
        return kept(verdict(dense.unpacked(h), graph=False, **search).select("serializable"))


def verdict(h: History, graph: bool = True, **search) -> DataFrame:
    """One row (serializable, reason, constraints), as timed() tells them: histories without predicates by explained() and told_by_graph()
    where they tell (graph: they are asked); then the order of ends is tried, and only where it, with what was searched around the places
    that it doesn't settle, doesn't prove the history, islands in the order of starts decide."""
    with scope(h.txns.sparkSession) as kept:
        h = h.but(txns=written(h.txns), ops=written(h.ops))
        made = written(known_edges(h, True)), written(constraint_rows(h, True, True))
        why = prelim.findings(h).agg(F.min("reason")).head()[0]  # a read that no order explains needs no search
        told = None
        if why is None and graph and h.preds is None:
            told = explained(h) or told_by_graph(h, made[0])
            why = "known_cycle" if told is False else None
        if why is None and not told and not by_ends(h, made, **search)[2]:
            return kept(_timed(h, True, True, True, made=made, **search).select("serializable", "reason", "constraints"))
        n = made[1].agg(F.countDistinct("cid").alias("constraints"))
        return kept(n.select(F.lit(why is None).alias("serializable"), F.lit(why).cast("string").alias("reason"), "constraints"))


def witness(h: History, **search) -> DataFrame:
    """(txn_id, place): an order that explains the history, places from 0. Islands come one after the other, those that need no
    search in the order of their starts. Only where timed() accepts."""
    with scope(h.txns.sparkSession) as kept:
        h = h.but(txns=written(h.txns), ops=written(h.ops))
        made = written(known_edges(h, True)), written(constraint_rows(h, True, True))
        places, found, proved = by_ends(h, made, **search)
        if proved and found is None:
            return kept(places.select("txn_id", F.col("idx").alias("place")))
        b = written((places if proved else bounds(h)).select("txn_id", "idx"))
        found = written((found if proved else by_island(h, made=made, **search)).select("island", "ord"))
        placed = found.select("island", F.posexplode("ord").alias("pos", "txn_id"))
        met = b.join(placed, "txn_id", "left").select("txn_id", F.coalesce("island", "idx").alias("at"), F.coalesce("pos", F.lit(0)).alias("pos"))
        return kept(ranked(met, "at", ["pos", "txn_id"], "place").select("txn_id", "place"))


def replay(h: History, order: DataFrame) -> DataFrame:
    """(txn_id, op_seq, obj, ver, sees): what each read of a committed transaction sees if the transactions run one after the other in
    `order` (txn_id, place)."""
    rows = h.ops.filter("obj IS NOT NULL").join(order, "txn_id").withColumn("wrote", F.when(F.col("kind") == "w", F.col("ver")))
    keyed = rows.withColumn("at", F.col("place"))
    # a running last value: the greatest (place, op_seq) of a write so far, and its version
    last = F.when(F.col("wrote").isNotNull(), F.struct("place", "op_seq", "wrote"))
    seen = running_all(keyed, "at", ["op_seq", "kind"], {"last": ("max", last, True)}, ["obj"])
    return seen.filter("kind <> 'w' AND ver IS NOT NULL").select("txn_id", "op_seq", "obj", "ver", F.coalesce("last.wrote", F.lit(INITIAL)).cast("long").alias("sees"))


def witness_cycles(h: History, **search) -> DataFrame:
    """(island, reason, step, src, dst, kind): the edges of one cycle of each island that can't be serialised, in order; kind is known,
    chosen (the last option of a constraint) or time."""
    bad = by_island(h.but(txns=written(h.txns), ops=written(h.ops)), **search).filter("NOT ok")
    return bad.select("island", "reason", F.posexplode("cycle").alias("step", "x")).select("island", "reason", "step", "x.*")


def timed(h: History, use_time_edges: bool = True, predicates: bool = True, read_checks: bool = True, **search) -> DataFrame:
    """One row: serializable (null: out of time), reason, islands, largest_island, constraints, residual, cells (of the islands' closures).
    It is decided when this is called, and the tables on the way are removed."""
    with scope(h.txns.sparkSession) as kept:
        return kept(_timed(h.but(txns=written(h.txns), ops=written(h.ops)), use_time_edges, predicates, read_checks, **search))


def _timed(h: History, use_time_edges: bool, predicates: bool, read_checks: bool, **search) -> DataFrame:
    found = by_island(h, use_time_edges, predicates, **search)
    parts = found.agg(
        F.count("*").alias("islands"), F.coalesce(F.max("txns"), F.lit(0)).alias("largest_island"), F.coalesce(F.sum("constraints"), F.lit(0)).alias("constraints"),
        F.coalesce(F.sum("residual"), F.lit(0)).alias("residual"), F.coalesce(F.sum("cells"), F.lit(0)).alias("cells"), F.max(F.when(~F.col("ok"), F.col("reason"))).alias("bad"), F.max(F.when(F.col("ok").isNull(), F.lit("timeout"))).alias("late"),
    )
    reads = prelim.findings(h, predicates) if read_checks else prelim.findings(h, False).filter("false")
    reads = reads.agg(F.min("reason").alias("read"))
    both = parts.withColumn("one", F.lit(1)).join(reads.withColumn("one", F.lit(1)), "one")  # a row each
    reason = F.coalesce("read", "bad", "late")
    return both.select(
        F.when(reason.isNull(), True).when(reason == "timeout", F.lit(None)).otherwise(False).alias("serializable"), reason.alias("reason"), "islands", "largest_island", "constraints", "residual", "cells"
    )
