"""Small histories with a known answer: 36 anomalies in four families, worked examples, and serial twins.

Each is (txns, ops) or (txns, ops, vers, preds) for build.inline; times are microseconds. Readers that pin a version order come after
the writers they tell apart. Operations of one transaction come in the order they are listed in.
"""

from __future__ import annotations

from pyspark.sql import SparkSession

from orderproof import schema
from orderproof.histories import build
from orderproof.schema import History

X, Y, Z, V = "part:1", "part:2", "part:3", "part:4"
A, B, C, D = (1, 0, 100), (2, 1, 101), (3, 2, 102), (4, 3, 103)


def _w(t, o, v):
    return (t, "w", o, v)


def _r(t, o, v):
    return (t, "r", o, v)


def _p(t, o, v, p=1):
    return (t, "pr", o, v, p)


#: name: (class, txns, ops), none of them serializable.
ITEM = {
    "aborted_read": ("RAT", [(1, 0, 10, "a"), (2, 5, 20)], [_w(1, X, 5), _r(2, X, 5)]),
    "intermediate_read": ("RAT", [A, B], [_w(1, X, 5), _w(1, X, 6), _r(2, X, 5)]),
    "non_repeatable_read": ("RAT", [A, B, C], [_w(1, X, 1), _w(2, X, 2), _r(3, X, 1), _r(3, X, 2)]),
    "read_skew": ("RAT", [A, B], [_w(1, X, 1), _w(1, Y, 1), _r(2, X, 1), _r(2, Y, 0)]),
    "read_skew_3": ("RAT", [A, B, C], [_w(1, X, 1), _w(1, Y, 1), _r(2, Y, 1), _w(2, Z, 2), _r(3, Z, 2), _r(3, X, 0)]),
    "long_fork": ("RAT", [A, B, C, D], [_w(1, X, 1), _w(2, Y, 2), _r(3, X, 1), _r(3, Y, 0), _r(4, X, 0), _r(4, Y, 2)]),
    "causal_violation": ("RAT", [A, B, C], [_w(1, X, 1), _r(2, X, 1), _w(2, Y, 2), _r(3, Y, 2), _r(3, X, 0)]),
    "stale_read": ("RAT", [(1, 0, 10), (2, 20, 30)], [_w(1, X, 1), _r(2, X, 0)]),
    "dirty_write": ("WAT", [A, B, (3, 200, 300), (4, 301, 400)], [_w(1, X, 1), _w(2, X, 2), _w(1, Y, 3), _w(2, Y, 4), _r(3, X, 2), _r(4, Y, 3)]),
    "dirty_write_3": ("WAT", [A, B, C, (4, 200, 300)], [_w(1, X, 1), _w(2, X, 2), _w(2, Y, 3), _w(3, Y, 4), _w(3, Z, 5), _w(1, Z, 6), _r(4, X, 2), _r(4, Y, 4), _r(4, Z, 6)]),
    "dirty_write_4": (
        "WAT", [A, B, C, D, (5, 200, 300)],
        [_w(1, X, 1), _w(1, V, 8), _w(2, X, 2), _w(2, Y, 3), _w(3, Y, 4), _w(3, Z, 5), _w(4, Z, 6), _w(4, V, 7), _r(5, X, 2), _r(5, Y, 4), _r(5, Z, 6), _r(5, V, 8)],
    ),
    "lost_update": ("WAT", [A, B], [_r(1, X, 0), _w(1, X, 1), _r(2, X, 0), _w(2, X, 2)]),
    "blind_write_against_time": ("WAT", [(1, 0, 10), (2, 20, 30), (3, 40, 50)], [_w(1, X, 1), _w(2, X, 2), _r(3, X, 1)]),
    "write_chain_with_reader": ("WAT", [A, B, C, (4, 200, 300)], [_r(2, X, 1), _w(1, X, 1), _w(2, X, 2), _r(3, X, 1), _w(3, X, 3), _r(4, X, 3)]),
    "lost_self_update": ("WAT", [A, B], [_r(1, X, 0), _w(1, X, 1), _w(1, X, 2), _r(2, X, 0), _w(2, X, 3), _w(2, X, 4)]),
    "write_skew": ("IAT", [A, B], [_r(1, X, 0), _w(1, Y, 1), _r(2, Y, 0), _w(2, X, 2)]),
    "write_skew_3": ("IAT", [A, B, C], [_r(1, X, 0), _w(1, Y, 1), _r(2, Y, 0), _w(2, Z, 2), _r(3, Z, 0), _w(3, X, 3)]),
    "write_skew_with_observer": ("IAT", [A, B, (3, 200, 300)], [_r(1, X, 0), _r(1, Y, 0), _w(1, X, 1), _r(2, X, 0), _r(2, Y, 0), _w(2, Y, 2), _r(3, X, 1), _r(3, Y, 2)]),
}
#: name: (class, serializable, txns, ops, vers (obj, ver, txn, v1), preds (id, domain, lo, hi))
ONE = [(1, "part", 1, 1)]
EMPTY = [(X, 0, 0, 0), (Y, 0, 0, 0), (Z, 0, 0, 1)]
PREDICATE = {
    "aborted_predicate_read": ("RAT", False, [(1, 0, 10, "a"), (2, 5, 20)], [_w(1, X, 5), _p(2, X, 5)], [(X, 0, 0, 0), (X, 5, 1, 1)], ONE),
    "intermediate_predicate_read": ("RAT", False, [A, B], [_w(1, X, 5), _w(1, X, 6), _p(2, X, 5)], [(X, 0, 0, 0), (X, 5, 1, 1), (X, 6, 1, 1)], ONE),
    "phantom": ("RAT", False, [(1, 0, 10), (2, 20, 30)], [_w(1, X, 5), _w(1, Y, 7), _p(2, Y, 7)], [(X, 5, 1, 1), (Y, 7, 1, 1), (X, 0, 0, 0), (Y, 0, 0, 0)], ONE),
    "predicate_read_skew": ("RAT", False, [A, B], [_w(1, X, 5), _w(1, Y, 6), _p(2, X, 5)], [(X, 0, 0, 0), (Y, 0, 0, 0), (X, 5, 1, 1), (Y, 6, 1, 1)], ONE),
    "lingering_match": ("RAT", False, [(1, 0, 10), (2, 20, 30)], [_w(1, X, 5), _p(2, X, 0)], [(X, 0, 0, 1), (X, 5, 1, 0)], ONE),
    "lost_update_by_predicate": ("WAT", False, [A, B], [_p(1, X, 0), _w(1, X, 1), _p(2, X, 0), _w(2, X, 2)], [(X, 0, 0, 1), (X, 1, 1, 1), (X, 2, 2, 1)], ONE),
    "predicate_write_race": (
        "WAT", False, [A, B, (3, 200, 300)], [_p(1, X, 0), _p(1, Y, 0), _w(1, X, 1), _w(1, Y, 3), _p(2, X, 0), _p(2, Y, 0), _w(2, X, 2), _w(2, Y, 4), _r(3, X, 2), _r(3, Y, 3)],
        [(X, 0, 0, 1), (Y, 0, 0, 1), (X, 1, 1, 0), (Y, 3, 1, 0), (X, 2, 2, 0), (Y, 4, 2, 0)], ONE,
    ),
    "predicate_write_skew": ("IAT", False, [A, B], [_p(1, Z, 0), _w(1, X, 5), _p(2, Z, 0), _w(2, Y, 6)], [*EMPTY, (X, 5, 1, 1), (Y, 6, 2, 1)], ONE),
    "mixed_skew": ("IAT", False, [A, B], [_r(1, X, 0), _w(1, Y, 5), _p(2, Z, 0), _w(2, X, 2)], [*EMPTY, (Y, 5, 1, 1), (X, 2, 2, 0)], ONE),
    "predicate_skew_3": (
        "IAT", False, [A, B, C], [_p(1, None, None, 2), _w(1, X, 1), _p(2, None, None, 3), _w(2, Y, 2), _p(3, None, None, 1), _w(3, Z, 3)],
        [(X, 0, 0, 0), (Y, 0, 0, 0), (Z, 0, 0, 0), (X, 1, 1, 1), (Y, 2, 2, 2), (Z, 3, 3, 3)], [(1, "part", 1, 1), (2, "part", 2, 2), (3, "part", 3, 3)],
    ),
    "veto_by_time": (
        "IAT", False, [(1, 0, 20), (2, 1, 8), (3, 10, 25), (4, 30, 35)], [_w(1, Y, 1), _w(2, Y, 2), _p(3, Z, 0), _r(4, Y, 2)],
        [(Y, 1, 1, 0), (Y, 2, 2, 1), (Z, 0, 0, 1)], ONE,
    ),
}
#: Anomalies among other transactions, without times of operations.
REAL = {f"real_{n}": (n, around) for n, around in (("lost_update", 5), ("write_skew", 8), ("read_skew", 6), ("long_fork", 12), ("causal_violation", 20), ("dirty_write", 9), ("non_repeatable_read", 7))}
#: What else has a known answer.
OTHER = {
    "orphan_read": (False, [A], [_r(1, X, 99)], [], []),
    "own_read_before_write": (False, [A], [_r(1, X, 5), _w(1, X, 5)], [], []),
    "own_write_overlooked": (False, [A], [_w(1, X, 5), _r(1, X, 0)], [], []),
    "own_write_seen": (True, [A], [_r(1, X, 0), _w(1, X, 5), _r(1, X, 5), _w(1, X, 6), _r(1, X, 6)], [], []),
    "own_match_after_reading": (True, [A], [_p(1, Y, 0), _w(1, X, 5)], [(X, 0, 0, 0), (X, 5, 1, 1), (Y, 0, 0, 1)], ONE),
    "own_update_out_of_range": (True, [A], [_w(1, X, 5), _p(1, Y, 0)], [(X, 0, 0, 1), (X, 5, 1, 0), (Y, 0, 0, 1)], ONE),
    "own_match_left_out": (False, [A], [_w(1, X, 5), _p(1, Y, 0)], [(X, 0, 0, 0), (X, 5, 1, 1), (Y, 0, 0, 1)], ONE),
    "returned_without_match": (False, [A], [_p(1, X, 0)], [(X, 0, 0, 0)], ONE),
    "worked_example": (
        False, [(1, 0, 100), (2, 1, 101), (3, 2, 102), (4, 3, 103)],
        [x for t in (1, 2, 3) for x in (_w(t, X, t), _w(t, Y, t))] + [_p(4, X, 2)],
        [(o, t, t, t - 1) for t in (1, 2, 3) for o in (X, Y)], ONE,
    ),
    "free_candidate": (
        True, [(1, 0, 2), (2, 5, 15), (3, 6, 14)], [_w(1, Y, 1), _p(2, X, 0), _r(2, Z, 0), _w(3, Y, 3), _w(3, Z, 4)],
        [(X, 0, 0, 1), (Y, 1, 1, 0), (Y, 3, 3, 0), (Z, 0, 0, 0), (Z, 4, 3, 0), ("other:1", 0, 0, 0)], ONE,
    ),
    "serial_predicates": (True, [(1, 0, 10), (2, 20, 30), (3, 40, 50)], [_w(1, X, 5), _p(2, X, 5), _w(3, Y, 6)], [(X, 5, 1, 1), (Y, 6, 3, 1), (X, 0, 0, 0), (Y, 0, 0, 0)], ONE),
}


def anomalies() -> dict[str, str]:
    """The 36 anomalies and their classes."""
    return {n: x[0] for n, x in (ITEM | PREDICATE).items()} | dict.fromkeys(REAL, "Real")


def names() -> list[str]:
    return [*anomalies(), *OTHER]


def rows(name: str) -> tuple[bool, list, list, list, list]:
    """(serializable, txns, ops, vers, preds) as build.inline takes them."""
    if name in ITEM:
        return (False, *ITEM[name][1:], [], [])
    if name in PREDICATE:
        return PREDICATE[name][1:]
    if name in OTHER:
        return OTHER[name]
    base, around = REAL[name]
    _, txns, ops = ITEM[base]
    other = {X: "customer:1", Y: "customer:2", Z: "order:1", V: "order:2"}
    ops = [(t, k, other[o], v) for t, k, o, v in ops]
    seen = 0
    for k in range(around):  # payments and orders of another customer, one after the other, beside the anomaly
        t = 50 + k
        txns, ops = [*txns, (t, 10 * k, 10 * k + 9)], [*ops, _r(t, "customer:9", seen), _w(t, "customer:9", 1000 + k), _w(t, f"order:{100 + k}", 2000 + k)]
        seen = 1000 + k
    return False, txns, ops, [], []


def twin(name: str) -> tuple[bool, list, list, list, list]:
    """The same transactions one after the other, what they read being what is there then; serializable by construction."""
    _, txns, ops, vers, preds = rows(name)
    value = {(o, v): x for o, v, _, x in vers}
    state: dict[str, int] = {}
    objects = sorted({o for o, *_ in vers})
    done, asked = [], set()
    for t in sorted(x[0] for x in txns):
        for op in (x for x in ops if x[0] == t):
            if op[1] == "w":
                state[op[2]] = op[3]
                done.append(op)
            elif op[1] == "r":
                done.append(_r(t, op[2], state.get(op[2], 0)))
            elif (t, op[4]) not in asked:
                asked.add((t, op[4]))
                low, high = next((lo, hi) for p, _, lo, hi in preds if p == op[4])
                hit = [o for o in objects if low <= value.get((o, state.get(o, 0)), low - 1) <= high]
                done += [_p(t, o, state.get(o, 0), op[4]) for o in hit] or [_p(t, None, None, op[4])]
    return True, [(t, 10 * k, 10 * k + 5) for k, t in enumerate(sorted(x[0] for x in txns))], done, vers, preds


def get(spark: SparkSession, name: str, make=rows) -> tuple[History, bool]:
    """(history, whether it is serializable)."""
    ok, txns, ops, vers, preds = make(name)
    h = build.inline(spark, txns, ops, vers, preds)
    return (h if preds else h.but(vers=None, preds=None)), ok


#: Ids of one fixture among several begin at its number times this.
STEP = 100


def together(spark: SparkSession, chosen: list[str], make=rows) -> History:
    """Several fixtures as one history: with their own ids (number of the fixture * STEP + id), objects, domains and time. Operations
    of all but the real-world style have times of their own."""
    tables: list[list] = [[], [], [], []]
    for k, name in enumerate(chosen):
        _, txns, ops, vers, preds = make(name)
        own = lambda o, k=k: None if o is None else f"f{k}.{o}"
        at, begin = k * 100_000, {x[0]: x[1] for x in txns}
        tables[0] += [(k * STEP + x[0], min(x[0], 50), max(0, x[0] - 50), x[3] if len(x) > 3 else "c", at + x[1], at + x[2], name) for x in txns]
        for n, x in enumerate(ops):
            s = None if name in REAL else at + begin[x[0]] + sum(y[0] == x[0] for y in ops[:n])
            tables[1].append((k * STEP + x[0], n, x[1], own(x[2]), x[3], k * STEP + x[4] if len(x) > 4 else None, s, None if s is None else s + 1))
        tables[2] += [(own(o), v, k * STEP + t if t else 0, float(x), None, False) for o, v, t, x in vers]
        tables[3] += [(k * STEP + p, f"f{k}.{d}", "v1", float(lo), float(hi)) for p, d, lo, hi in preds]
    return History(*(spark.createDataFrame(rows, kind) for rows, kind in zip(tables, (schema.TXNS, schema.OPS, schema.VERS, schema.PREDS), strict=True)))
