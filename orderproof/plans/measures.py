"""Measures: anomalies found by each method, constraints left after each step, and costs of closures."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from orderproof.baselines import polygraph, protocol, small
from orderproof.functions import cdcl
from orderproof.functions import closure as cl
from orderproof.functions.solver import solve
from orderproof.histories import build, fixtures
from orderproof.operators import constraints as cs
from orderproof.operators import prelim
from orderproof.plans import islands, verify
from orderproof.plans.bounds import bounds
from orderproof.plans.global_order import ranked
from orderproof.schema import History
from orderproof.sources.scratch import scope, written

METHODS = ["timed", "polygraph", "frontier", "protocol"]


def detection(spark: SparkSession, make=fixtures.rows) -> DataFrame:
    """(name, class, timed, polygraph, frontier, protocol): whether each method rejects each of the 36 anomalies, which stand side by side
    in one history. The protocol checker's null is that it abstains, for want of operation times."""
    kinds = fixtures.anomalies()
    names = list(kinds)
    h = fixtures.together(spark, names, make)
    h = h.but(txns=written(h.txns), ops=written(h.ops))
    step = fixtures.STEP
    case = lambda c: F.floor(F.col(c) / step).cast("long")
    own = lambda b: b.withColumn("island", case("txn_id"))
    hit = lambda df, m: df.select("case_no").distinct().withColumn(m, F.lit(True))
    bad = verify.by_island(h).filter("NOT ok").select(case("first").alias("case_no"))
    timed = hit(bad.unionAll(prelim.findings(h).select(case("reader").alias("case_no"))), "timed")
    poly = hit(verify.by_island(h, timed=False, predicates=False, cut=own).filter("NOT ok").select(case("first").alias("case_no")), "polygraph")
    front = hit(small.run(h, lambda t, x: {"f": small.frontier(t)}, step).filter("value = 0"), "frontier")
    flagged = hit(protocol.overlapping_updates(h).select(case("i").alias("case_no")), "flagged")
    times = h.ops.groupBy(case("txn_id").alias("case_no")).agg((F.count("op_s") == F.count("*")).alias("told"))
    out = spark.createDataFrame([(k, n, kinds[n]) for k, n in enumerate(names)], "case_no long, name string, class string")
    for df in (timed, poly, front, flagged, times):
        out = out.join(df, "case_no", "left")
    no = lambda c: F.coalesce(c, F.lit(False)).alias(c)
    return out.select("name", "class", no("timed"), no("polygraph"), no("frontier"), F.when(F.col("told"), F.coalesce("flagged", F.lit(False))).alias("protocol"))


def detection_cube(spark: SparkSession) -> DataFrame:
    """Anomalies and those found, by class and in all."""
    d = detection(spark)
    return d.rollup("class").agg(F.count("*").alias("anomalies"), *(F.count_if(m).alias(m) for m in METHODS)).withColumn("class", F.coalesce("class", F.lit("all")))


def detection_pivot(spark: SparkSession) -> DataFrame:
    """Share found, a row a method and a column a class."""
    long = detection(spark).unpivot(["class"], METHODS, "method", "found")
    return long.groupBy("method").pivot("class", ["RAT", "WAT", "IAT", "Real"]).agg(F.round(F.avg(F.coalesce("found", F.lit(False)).cast("int")), 4))


#: What is true of the fixtures: none is serializable, so a method without gaps finds all.
TRUTH = ", ".join(f"('{n}', '{c}')" for n, c in fixtures.anomalies().items())
TIMED_SQL = f"SELECT name, class, true AS timed FROM (VALUES {TRUTH}) t(name, class)"


def histories(spark: SparkSession, sf_dir: str) -> dict[str, History]:
    """The five histories of the constraint comparison."""
    out = {m: build.registers(spark, sf_dir, m) for m in ("wh", "wr", "rh")}
    return out | {"social": build.social(spark, sf_dir), "orders": build.orders_mix(spark, sf_dir)}


def constraint_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(workload, total, overlapping): pairs of writers over all objects, and those that client times leave open."""
    out = None
    for name, h in histories(spark, sf_dir).items():
        total = cs.item_pair_counts(h).agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("total")).withColumn("one", F.lit(1))
        left = cs.item_pairs(h).agg(F.count("*").alias("overlapping")).withColumn("one", F.lit(1))
        row = total.join(left, "one").select(F.lit(name).alias("workload"), "total", "overlapping")
        out = row if out is None else out.unionAll(row)
    return out


#: Pairs up to which the polygraph baseline is run: it makes them all.
POLYGRAPH_PAIRS = 5_000_000


def constraint_reduction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(workload, total, polygraph, overlapping, residual): pairs of writers; what pruning by reachability along read dependencies alone
    leaves of them (null: more than POLYGRAPH_PAIRS, not run); pairs that overlap, joined over objects; and what pruning leaves of these
    to the search."""
    out = None
    for name, h in histories(spark, sf_dir).items():
        h = h.but(txns=written(h.txns), ops=written(h.ops))
        total = cs.item_pair_counts(h).agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("total")).withColumn("one", F.lit(1))
        left = verify.timed(h).select("constraints", "residual").withColumn("one", F.lit(1))
        many = (total.head().total or 0) > POLYGRAPH_PAIRS
        poly = spark.range(1).select(F.lit(None).cast("long").alias("polygraph")) if many else polygraph.residual(h).agg(F.count("*").alias("polygraph"))
        poly = poly.withColumn("one", F.lit(1))
        row = total.join(left, "one").join(poly, "one").select(F.lit(name).alias("workload"), "total", "polygraph", F.col("constraints").alias("overlapping"), "residual")
        out = row if out is None else out.unionAll(row)
    return out


def constraint_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Constraint counts by workload and stage with their sums: (workload, stage, n)."""
    long = constraint_counts(spark, sf_dir).unpivot(["workload"], ["total", "overlapping"], "stage", "n")
    return long.groupingSets([["workload", "stage"], ["stage"]], "workload", "stage").agg(F.sum("n").alias("n")).withColumn("workload", F.coalesce("workload", F.lit("all")))


def _graph(h: History) -> DataFrame:
    t = h.txns.filter("status = 'c'").select(F.lit("t").alias("kind"), F.col("txn_id").alias("a"), F.lit(None).cast("long").alias("b"), "s", "e")
    none = F.lit(None).cast("long")
    return t.unionAll(verify.known_edges(h, True).select(F.lit("k").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), none.alias("s"), none.alias("e")))


def _indexed(pdf: pd.DataFrame) -> tuple[list, list, list]:
    t = pdf[pdf.kind == "t"].sort_values(["s", "a"])
    at = {int(x): i for i, x in enumerate(t.a)}
    edges = [(at[int(u)], at[int(v)]) for u, v in zip(*(pdf.loc[pdf.kind == "k", c] for c in "ab"), strict=True)]
    return [int(x) for x in t.s], [int(x) for x in t.e], edges


BUILDS = ["timed_purdom", "timed_italiano", "timed_dict", "purdom", "italiano", "warshall"]


def closure_costs(h: History, methods: list[str] = BUILDS) -> DataFrame:
    """(method, pairs, cells, seconds) for building the closure of the known graph and time. Only the building is timed; what it needs
    (successor lists; for the full ones all time edges, as bit rows) is made before, and pairs, which agree between methods, are counted
    after."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        s, e, edges = _indexed(pdf)
        n = len(s)
        succ = [set() for _ in range(n)]
        for u, v in edges:
            succ[u].add(v)
        full = []
        if {"purdom", "italiano", "warshall"} & set(methods):
            full = [a | b for a, b in zip(cl.by_time(s, e)[0], cl.adjacent(n, edges), strict=True)]

        def grown(kind):
            b = kind(s, e)
            for u, v in edges:
                b.insert(u, v)
            return b

        def built(kind):
            b = kind(s, e)
            b.build(succ)
            return b

        how = {
            "timed_purdom": lambda: built(cl.Band), "timed_italiano": lambda: grown(cl.Band), "timed_dict": lambda: built(cl.DictBand),
            "purdom": lambda: cl.purdom_rows(full), "italiano": lambda: cl.italiano_rows(full), "warshall": lambda: cl.warshall_rows(full),
        }
        rows = []
        for name in methods:
            began = time.perf_counter()
            got = how[name]()
            took = time.perf_counter() - began
            if isinstance(got, cl.Band):  # what a row doesn't hold is reachable by time
                pairs, cells = sum(got.row[i].bit_count() + n - 1 - got.r[i] for i in range(n)), got.cells()
            else:
                pairs, cells = sum(r.bit_count() for r in got), n * n
            rows.append((name, int(pairs), int(cells), took))
        return pd.DataFrame(rows, columns=["method", "pairs", "cells", "seconds"])

    return _graph(h).groupBy(F.lit(0).alias("one")).applyInPandas(work, "method string, pairs long, cells long, seconds double")


def update_costs(h: History, batch: int = 50) -> DataFrame:
    """(method, pairs, looked, seconds) for adding the read dependencies one by one to the closure of time: in the band, in a full closure
    edge by edge, or by making the full one anew after each `batch` edges. looked: rows that the band's insertions considered, of
    n times as many in a full one."""

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        s, e, edges = _indexed(pdf)
        n = len(s)
        time_row, time_col = cl.by_time(s, e)
        rows = []
        began = time.perf_counter()
        b = cl.Band(s, e)
        for u, v in edges:
            b.insert(u, v)
        rows.append(("timed", sum(b.row[i].bit_count() + n - 1 - b.r[i] for i in range(n)), b.looked, time.perf_counter() - began))
        began = time.perf_counter()
        f = cl.Full(n, time_row, time_col)  # time edges are closed by themselves
        for u, v in edges:
            f.insert(u, v)
        rows.append(("italiano", sum(r.bit_count() for r in f.row), n * len(edges), time.perf_counter() - began))
        began = time.perf_counter()
        full, now = time_row, list(time_row)
        for k in range(0, len(edges), batch):
            for u, v in edges[k : k + batch]:
                now[u] |= 1 << v
            full = cl.purdom_rows(now)
        rows.append(("rebuild", sum(r.bit_count() for r in full), n * len(edges), time.perf_counter() - began))
        return pd.DataFrame([(a, int(b), int(c), d) for a, b, c, d in rows], columns=["method", "pairs", "looked", "seconds"])

    return _graph(h).groupBy(F.lit(0).alias("one")).applyInPandas(work, "method string, pairs long, looked long, seconds double")


def solver_costs(h: History, budget_s: float = 20.0, largest_plain: int = 40) -> DataFrame:
    """(island, txns, method, answer, variables, clauses, literals, conflicts, seconds): the islands of a history, without pruning, by the
    solver of this library and by three encodings for a general one, formulas included. The plain encoding's cubic formula isn't made
    for islands of more than `largest_plain` transactions (answer null)."""
    kind = "island long, txns long, method string, answer boolean, variables long, clauses long, literals long, conflicts long, seconds double"

    def compare(s, e, known, cons):
        out = []
        began = time.perf_counter()
        got = solve(s, e, known, cons, prune=False, budget_s=budget_s)
        out.append(("theory", got.ok, None, None, None, got.conflicts, time.perf_counter() - began))
        for name, run in cdcl.ENCODINGS.items():
            began = time.perf_counter()
            answer, size, conflicts = (None, (None,) * 3, 0) if name == "plain" and len(s) > largest_plain else run(s, e, known, cons, budget_s=budget_s)
            out.append((name, answer, *size, conflicts, time.perf_counter() - began))
        return out

    return verify.on_islands(h, compare, kind)


def prefixes(h: History, shares: int = 10) -> DataFrame:
    """(step, txns, pairs): histories of the first tenths of the transactions, by start: their number, and the overlapping pairs of writers
    of an object, which is what is left to decide."""
    place = ranked(h.txns.filter("status = 'c'").select("txn_id", "s"), "s", ["txn_id"])
    n = F.lit(place.count())
    step = F.least(F.lit(shares), F.floor(F.col("idx") * shares / n) + 1).cast("int")
    of = written(place.select("txn_id", step.alias("step")))
    pairs = cs.item_pairs(h).join(of.select(F.col("txn_id").alias("i"), F.col("step").alias("si")), "i").join(of.select(F.col("txn_id").alias("j"), F.col("step").alias("sj")), "j")
    count = lambda df, name: df.groupBy("step").agg(F.count("*").alias(name))
    met = count(of, "own").join(count(pairs.select(F.greatest("si", "sj").alias("step")), "more"), "step", "left")
    upto = W.orderBy("step").rowsBetween(W.unboundedPreceding, 0)  # a row a step
    return met.select("step", F.sum("own").over(upto).alias("txns"), F.coalesce(F.sum("more").over(upto), F.lit(0)).alias("pairs"))


def _spans(h: History, b: DataFrame, pairs: DataFrame) -> DataFrame:
    """(low, high): places between which each open pair of writers, with the readers of their versions, lies; no edges are made."""
    at = b.select("txn_id", "idx")
    w = prelim.installed(h).select("obj", "ver", "txn_id").join(at, "txn_id")
    seen = prelim.reads(h).select("obj", "ver", "txn_id").join(at, "txn_id").groupBy("obj", "ver").agg(F.min("idx").alias("low"), F.max("idx").alias("high"))
    w = w.join(seen, ["obj", "ver"], "left").select("obj", "txn_id", F.least("idx", "low").alias("low"), F.greatest("idx", "high").alias("high"))
    side = lambda c: w.select("obj", F.col("txn_id").alias(c), F.col("low").alias(f"{c}_low"), F.col("high").alias(f"{c}_high"))
    met = pairs.join(side("i"), ["obj", "i"]).join(side("j"), ["obj", "j"])
    return met.select(F.least("i_low", "j_low").alias("low"), F.greatest("i_high", "j_high").alias("high"))


def island_sizes(h: History) -> DataFrame:
    """One row (largest_island, constraints, cells), as verify.timed() tells them of a history without predicates, without its search:
    islands by what backward edges and open pairs span, and the bands of their closures from sorted times alone."""
    b = bounds(h)
    pairs = written(cs.item_pairs(h))
    at = lambda df, c: df.join(b.select(F.col("txn_id").alias(c), F.col("idx").alias(f"{c}_at")), c)
    back = at(at(verify.known_edges(h, True), "src"), "dst").filter("dst_at < src_at").select(F.col("dst_at").alias("low"), F.col("src_at").alias("high"))
    cover = written(back.unionAll(_spans(h, b, pairs)))
    cut = islands.assign(b, cover)
    busy = cut.join(cover.select(F.col("low").alias("idx")).distinct(), "idx", "left_semi").select("island").distinct()

    def band(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["s", "txn_id"])
        s, e = pdf.s.to_numpy(), pdf.e.to_numpy()
        cells = np.searchsorted(s, e, "left") - np.searchsorted(np.maximum.accumulate(e), s, "right")
        return pd.DataFrame([(len(s), int(cells.sum()))], columns=["txns", "cells"])

    sizes = cut.join(busy, "island", "left_semi").select("island", "txn_id", "s", "e").groupBy("island").applyInPandas(band, "txns long, cells long")
    total = sizes.agg(F.coalesce(F.max("txns"), F.lit(0)).alias("largest_island"), F.coalesce(F.sum("cells"), F.lit(0)).alias("cells")).withColumn("one", F.lit(1))
    n = pairs.select("i", "j").distinct().agg(F.count("*").alias("constraints")).withColumn("one", F.lit(1))
    return total.join(n, "one").select("largest_island", "constraints", "cells")  # a row each


def scaling(spark: SparkSession, h: History, shares: list[float]) -> DataFrame:
    """(txns, seconds, largest_island, constraints, cells): the verifier on prefixes of a history. seconds: of the verdict; what islands in
    the order of starts hold is counted apart. cells: of the islands' closures, which is the memory that grows."""
    rows = []
    with scope(spark):
        h = h.but(txns=written(h.txns), ops=written(h.ops))
        total = h.txns.count()
        for x in shares:
            part = build.prefix(h, int(total * x))
            part = part.but(txns=written(part.txns), ops=written(part.ops))
            began = time.perf_counter()
            verify.serializable(part).head()
            took = time.perf_counter() - began
            got = island_sizes(part).head()
            rows.append((int(total * x), took, got.largest_island, got.constraints, got.cells))
    return spark.createDataFrame(rows, "txns long, seconds double, largest_island long, constraints long, cells long")
