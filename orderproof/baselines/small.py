"""Exponential methods on small histories, for comparison and as oracles. Transactions are dicts: id, s, e, reads [(obj, ver)],
writes {obj: ver}, unknown [(pred, obj)]; `holds` maps (pred, obj, ver) to truth. Version 0 is the initial one."""

from __future__ import annotations

import itertools
import time

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orderproof.operators import prelim
from orderproof.schema import History


def serial_orders(txns: list[dict], holds: dict, first: bool = True, timed: bool = False) -> list[tuple]:
    """Orders in which every read sees the last write before it, its own transaction's included, and no object that a predicate read
    skipped matches; stops at the first one if asked. Depth first, pruned as soon as a read fails. A transaction's `steps` are
    (kind, object, version or predicate) in order; without them it reads first and writes then. timed: what ended no later than another
    began comes first."""
    found: list[tuple] = []

    def steps(t: dict) -> list[tuple]:
        if "steps" in t:
            return t["steps"]
        return [("r", o, v) for o, v in t["reads"]] + [("u", o, p) for p, o in t["unknown"]] + [("w", o, v) for o, v in t["writes"].items()]

    def after(t: dict, state: dict) -> dict | None:
        state = dict(state)
        for kind, o, x in steps(t):
            if kind == "w":
                state[o] = x
            elif kind == "r" and state.get(o, 0) != x or kind == "u" and holds.get((x, o, state.get(o, 0)), False):
                return None
        return state

    def go(order: tuple, state: dict, rest: frozenset) -> bool:
        if not rest:
            found.append(order)
            return first
        for i in sorted(rest):
            if timed and any(txns[j]["e"] <= txns[i]["s"] for j in rest):
                continue
            now = after(txns[i], state)
            if now is not None and go((*order, txns[i]["id"]), now, rest - {i}):
                return True
        return False

    go((), {}, frozenset(range(len(txns))))
    return found


def frontier(txns: list[dict], budget_s: float = 60.0) -> bool | None:
    """Extends a commit order by heads of sessions, breadth first over (positions, last writers); predicates play no part.
    None: out of time."""
    sessions: dict[int, list[dict]] = {}
    for t in sorted(txns, key=lambda t: (t["session"], t["pos"], t["s"], t["id"])):
        sessions.setdefault(t["session"], []).append(t)
    lines, stop = list(sessions.values()), time.monotonic() + budget_s
    states = {((0,) * len(lines), ())}
    for _ in range(len(txns)):
        nxt = set()
        for at, data in states:
            if time.monotonic() > stop:
                return None
            now = dict(data)
            for k, line in enumerate(lines):
                if at[k] < len(line) and all(now.get(o, 0) == v for o, v in line[at[k]]["reads"]):
                    nxt.add(((*at[:k], at[k] + 1, *at[k + 1 :]), tuple(sorted((now | line[at[k]]["writes"]).items()))))
        states = nxt
        if not states:
            return False
    return True


def _acyclic(edges: set, ids: list) -> bool:
    left, edges = set(ids), {x for x in edges if x[0] != x[1]}
    while left:
        free = [i for i in left if not any(v == i and u in left for u, v in edges)]
        if not free:
            return False
        left -= set(free)
    return True


def complete_histories(txns: list[dict], holds: dict):
    """Every completion: a version order per object and a version that doesn't match for each skipped one."""
    writers: dict[str, list] = {}
    for t in txns:
        for o in t["writes"]:
            writers.setdefault(o, []).append(t["id"])
    version = {(t["id"], o): v for t in txns for o, v in t["writes"].items()}
    skipped = [(t["id"], p, o) for t in txns for p, o in t["unknown"]]
    objs = sorted(writers)
    for orders in itertools.product(*(itertools.permutations(writers[o]) for o in objs)):
        order = dict(zip(objs, orders, strict=True))
        false = [[w for w in writers.get(o, []) if w != r and not holds.get((p, o, version[w, o]), False)] for r, p, o in skipped]
        for pick in itertools.product(*false):
            yield order, dict(zip(skipped, pick, strict=True))


def dsg_edges(txns: list[dict], holds: dict, order: dict, pick: dict) -> set:
    """Edges of one completion: item dependencies, and for skipped versions those to and from the nearest flips."""
    writer = {(o, v): t["id"] for t in txns for o, v in t["writes"].items()}
    version = {(t["id"], o): v for t in txns for o, v in t["writes"].items()}
    edges = {(a, b) for os in order.values() for a, b in itertools.pairwise(os)}
    for t in txns:
        for o, v in t["reads"]:
            w = writer.get((o, v))
            if w is not None:
                edges.add((w, t["id"]))
            later = order.get(o, ())[order[o].index(w) + 1 :] if w is not None else order.get(o, ())
            if later:
                edges.add((t["id"], later[0]))
    for (r, p, o), w in pick.items():
        at = order[o].index(w)
        truth = [holds.get((p, o, version[x, o]), False) for x in order[o]]
        flips = [k for k in range(len(truth)) if truth[k] != (truth[k - 1] if k else False)]
        before = [k for k in flips if k <= at]
        edges.add((order[o][before[-1]] if before else order[o][0], r))
        after = [k for k in flips if k > at]
        if after:
            edges.add((r, order[o][after[0]]))
    return edges


def exhaustive(txns: list[dict], holds: dict) -> tuple[int, int]:
    """(complete histories, serializable ones)."""
    ids, total, good = [t["id"] for t in txns], 0, 0
    for order, pick in complete_histories(txns, holds):
        total += 1
        good += _acyclic(dsg_edges(txns, holds, order, pick), ids)
    return total, good


def two_stage(txns: list[dict], holds: dict) -> bool:
    """Version orders first, item dependencies only; then the skipped versions of each order that is acyclic."""
    ids = [t["id"] for t in txns]
    tried: dict[tuple, bool] = {}
    for order, pick in complete_histories(txns, holds):
        key = tuple(sorted(order.items()))
        if key not in tried:
            tried[key] = _acyclic(dsg_edges(txns, holds, order, {}), ids)
        if tried[key] and _acyclic(dsg_edges(txns, holds, order, pick), ids):
            return True
    return False


def as_lists(pdf: pd.DataFrame) -> tuple[list[dict], dict]:
    txns = {}
    for r in pdf[pdf.kind == "t"].itertuples():
        txns[int(r.a)] = {"id": int(r.a), "s": int(r.x), "e": int(r.y), "session": int(r.b), "pos": int(r.z), "reads": [], "writes": {}, "unknown": []}
    holds = {}
    for r in pdf[pdf.kind != "t"].sort_values(["a", "z"]).itertuples():
        if r.kind == "h":
            holds[int(r.b), r.obj, int(r.x)] = bool(r.y)
        elif int(r.a) in txns:
            t = txns[int(r.a)]
            if r.kind == "w":
                t["writes"][r.obj] = int(r.x)
            elif r.kind == "u":
                t["unknown"].append((int(r.b), r.obj))
            else:
                t["reads"].append((r.obj, int(r.x)))
    return sorted(txns.values(), key=lambda t: (t["s"], t["id"])), holds


def run(h: History, method, group: int | None = None) -> DataFrame:
    """What `method` (txns, holds) -> dict gives, a row a measure; for small histories, whose rows meet in one worker. With `group` for
    each run of that many transaction ids on its own (column case_no), without predicates."""
    long = lambda c: F.col(c).cast("long") if isinstance(c, str) else c.cast("long")
    none = F.lit(None).cast("long")
    t = prelim.committed(h).select(F.lit("t").alias("kind"), F.col("txn_id").alias("a"), long("session_id").alias("b"), F.lit(None).cast("string").alias("obj"), F.col("s").alias("x"), F.col("e").alias("y"), long("session_pos").alias("z"))
    w = prelim.installed(h).select(F.lit("w").alias("kind"), F.col("txn_id").alias("a"), none.alias("b"), "obj", F.col("ver").alias("x"), none.alias("y"), none.alias("z"))
    own = prelim.writes(h).select("txn_id", "obj", "ver")
    r = prelim.reads(h).join(own, ["txn_id", "obj", "ver"], "left_anti").select(F.lit("r").alias("kind"), F.col("txn_id").alias("a"), none.alias("b"), "obj", F.col("ver").alias("x"), none.alias("y"), none.alias("z"))
    rows = t.unionAll(w).unionAll(r)
    if h.preds is not None and group is None:
        u = prelim.unknown_theta_reads(h).select(F.lit("u").alias("kind"), F.col("txn_id").alias("a"), long("pred_id").alias("b"), "obj", none.alias("x"), none.alias("y"), none.alias("z"))
        p = prelim.theta(h).select(F.lit("h").alias("kind"), none.alias("a"), long("pred_id").alias("b"), "obj", F.col("ver").alias("x"), long("holds").alias("y"), none.alias("z"))
        rows = rows.unionAll(u).unionAll(p)

    def work(key, pdf: pd.DataFrame) -> pd.DataFrame:
        got = method(*as_lists(pdf))
        return pd.DataFrame([(int(key[0]), k, None if v is None else int(v)) for k, v in got.items()], columns=["case_no", "measure", "value"])

    case = F.floor(F.col("a") / group).cast("long") if group else F.lit(0).cast("long")
    return rows.withColumn("case_no", case).groupBy("case_no").applyInPandas(work, "case_no long, measure string, value long")
