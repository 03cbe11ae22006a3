"""The baseline without client times, predicates and checks of read values: read dependencies are known, all pairs of writers are open."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderproof.functions.closure import Cycle, purdom
from orderproof.operators import constraints as cs
from orderproof.operators import deps, prelim
from orderproof.plans import verify as plan
from orderproof.plans.global_order import ranked
from orderproof.schema import INITIAL, History
from orderproof.sources.scratch import scope, written

#: Transactions up to which the closure, a square of bits, is made: 128 MB. The baseline's own cost is cubic.
LARGEST = 32_768


def verify(h: History, budget_s: float = 60.0, cut="none") -> DataFrame:
    return plan.timed(h, use_time_edges=False, predicates=False, read_checks=False, cut=cut, budget_s=budget_s)


def verdict(h: History, **search) -> DataFrame:
    """One row (serializable), as verify() tells it. An order is looked for first that needs no search and no pairs of writers: the order
    of ends is one choice among all, whatever times mean; only where reads contradict it verify() decides."""
    with scope(h.txns.sparkSession) as kept:
        h = h.but(txns=written(h.txns), ops=written(h.ops))
        if plan.ends_explain(h):
            return kept(h.txns.sparkSession.range(1).select(F.lit(True).alias("serializable")))
        return kept(verify(h, **search).select("serializable"))


def known(h: History) -> DataFrame:
    """(src, dst): writers before readers, readers of initial versions before all writers of the object."""
    first = prelim.reads(h).filter(F.col("ver") == INITIAL).select(F.col("txn_id").alias("src"), "obj")
    before = first.join(prelim.installed(h).select(F.col("txn_id").alias("dst"), "obj"), "obj").filter("src <> dst").select("src", "dst")
    return deps.item_wr(h).select("src", "dst").unionAll(before).distinct()


def residual(h: History, rounds: int = 50) -> DataFrame:
    """(i, j): pairs of writers that pruning leaves: a side goes if one of its edges closes a cycle of known ones, and the other side's
    edges are known from then on, until nothing moves. Raises Cycle where the history is refuted on the way, and ValueError beyond
    LARGEST transactions. The closure's bits are broadcast, and pairs are tested where they are."""
    spark = h.txns.sparkSession
    places = written(ranked(prelim.committed(h).select("txn_id", "s"), "s", ["txn_id"]).select("txn_id", "idx"))
    n = places.count()
    if n > LARGEST:
        raise ValueError(f"{n} transactions: the full closure is made for {LARGEST} at most")
    at = lambda df, c: df.join(places.select(F.col("txn_id").alias(c), F.col("idx").alias(f"{c}_at")), c)
    sets = written(at(at(cs.coalesced(cs.item_edge_sets(h, cs.item_pairs(h, timed=False))), "src"), "dst").select("i", "j", "side", F.col("src_at").cast("int").alias("src"), F.col("dst_at").cast("int").alias("dst")))
    edges = written(at(at(known(h), "src"), "dst").select(F.col("src_at").cast("int").alias("src"), F.col("dst_at").cast("int").alias("dst")))
    for _ in range(rounds):
        table = edges.toArrow()
        rows = purdom(n, list(zip(table["src"].to_pylist(), table["dst"].to_pylist(), strict=True)))
        width = -(-n // 8)
        told = spark.sparkContext.broadcast(b"".join(r.to_bytes(width, "little") for r in rows))

        def blocked(batches, told=told, width=width):
            bits = np.frombuffer(told.value, np.uint8).reshape(-1, width)
            for batch in batches:
                u, v = (batch.column(c).to_numpy() for c in ("src", "dst"))
                reach = lambda a, b: pa.array(((bits[a, b >> 3] >> (b & 7).astype(np.uint8)) & 1).astype(bool))
                yield pa.RecordBatch.from_arrays([*batch.columns, reach(v, u), reach(u, v)], [*batch.schema.names, "back", "have"])

        tested = sets.mapInArrow(blocked, "i long, j long, side int, src int, dst int, back boolean, have boolean")
        state = written(tested.groupBy("i", "j").agg(F.max(F.when(F.col("side") == 0, F.col("back"))).alias("no0"), F.max(F.when(F.col("side") == 1, F.col("back"))).alias("no1")))
        if state.filter("no0 AND no1").limit(1).count():
            raise Cycle([])
        forced = state.filter("no0 OR no1").select("i", "j", F.when(F.col("no0"), 1).otherwise(0).alias("side"))
        if not forced.limit(1).count():
            break
        # what follows already isn't added: few edges come to the driver
        edges = written(edges.unionAll(tested.filter("NOT have").join(forced, ["i", "j", "side"], "left_semi").select("src", "dst")).distinct())
        sets = written(sets.join(state.filter("NOT no0 AND NOT no1").select("i", "j"), ["i", "j"], "left_semi"))
    return sets.select("i", "j").distinct()
