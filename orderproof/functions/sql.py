"""The verifier for SQL users: views of a history and its graph, and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from orderproof.operators import constraints as cs
from orderproof.plans import verify
from orderproof.schema import History
from orderproof.sources.scratch import written


def register_views(h: History, prefix: str = "") -> list[str]:
    """Temporary views history_txns, history_ops, history_vers, history_preds (where there are any), known_edges, item_constraints,
    predicate_constraints and verdict, each name behind `prefix`. Returns the names."""
    views = {"history_txns": h.txns, "history_ops": h.ops, "known_edges": written(verify.known_edges(h, True)), "item_constraints": written(cs.coalesced(cs.item_edge_sets(h, cs.item_pairs(h)))), "verdict": verify.timed(h)}
    if h.preds is not None:
        views |= {"history_vers": h.vers, "history_preds": h.preds, "predicate_constraints": written(cs.predicate(h, cs.unmet(h)))}
    for name, df in views.items():
        df.createOrReplaceTempView(f"{prefix}{name}")
    return [f"{prefix}{n}" for n in views]


def _enumerate_orders():
    @F.udtf(returnType="place int, item int, number int")
    class EnumerateOrders:
        """enumerate_orders(n): all orders of 0 .. n-1, a row a place; n is 8 at most."""

        def eval(self, n: int):
            import itertools

            if n > 8:
                raise ValueError("orders of 8 items at most")
            for number, order in enumerate(itertools.permutations(range(n))):
                for place, item in enumerate(order):
                    yield place, item, number

    return EnumerateOrders


def _path_of():
    @F.udtf(returnType="step int, src long, dst long")
    class PathOf:
        """path_of(table of edges (src, dst), a, b): the edges of a shortest path, if there is one. For the edges of one island."""

        def __init__(self):
            self.out: dict[int, list[int]] = {}
            self.ends = None

        def eval(self, row, a: int, b: int):
            self.out.setdefault(row["src"], []).append(row["dst"])
            self.ends = a, b

        def terminate(self):
            if self.ends is None:
                return
            a, b = self.ends
            came, todo = {a: None}, [a]
            for x in todo:
                for y in self.out.get(x, []):
                    if y not in came:
                        came[y] = x
                        todo.append(y)
            if b in came and a != b:
                path = [b]
                while path[-1] != a:
                    path.append(came[path[-1]])
                path.reverse()
                for k, (u, v) in enumerate(zip(path, path[1:], strict=False)):
                    yield k, u, v

    return PathOf


def _serial_violations():
    @F.udtf(returnType="island long, serializable boolean, reason string, step int, src long, dst long, kind string")
    class SerialViolations:
        """serial_violations(table of island rows, as verify.island_rows() gives them, partitioned by island): the verdict on each island and,
        where it can't be serialised, the edges of a cycle."""

        def __init__(self):
            self.rows = []

        def eval(self, row):
            self.rows.append(row.asDict())

        def terminate(self):
            from orderproof.functions.solver import solve
            from orderproof.plans.verify import _island

            if not self.rows:
                return
            ids, s, e, known, cons = _island(pd.DataFrame(self.rows))
            out = solve(s, e, known, cons)
            island = int(self.rows[0]["island"])
            if not out.cycle:
                yield island, out.ok, out.reason, None, None, None, None
            for k, (u, v, kind) in enumerate(out.cycle):
                yield island, out.ok, out.reason, k, ids[u], ids[v], kind

    return SerialViolations


def _has_cycle():
    @F.pandas_udf("boolean")
    def has_cycle(src: pd.Series, dst: pd.Series) -> bool:
        """Whether the edges of a group hold a cycle."""
        from orderproof.functions.closure import schedule

        ids = {x: i for i, x in enumerate(sorted({*src, *dst}))}
        return bool(ids) and not schedule([0] * len(ids), [1] * len(ids), [(ids[u], ids[v]) for u, v in zip(src, dst, strict=True)])[0]

    return has_cycle


def band_get(bits, place):
    """Whether the bit `place` of a packed row (binary, least bit first) is set."""
    byte = F.conv(F.hex(F.substr(bits, F.floor(place / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return F.call_function("shiftright", byte, F.pmod(place, F.lit(8)).cast("int")).bitwiseAND(F.lit(1)) == 1


def register_functions(spark: SparkSession) -> None:
    """enumerate_orders, path_of and serial_violations as table functions, has_cycle as an aggregate."""
    spark.udtf.register("enumerate_orders", _enumerate_orders())
    spark.udtf.register("path_of", _path_of())
    spark.udtf.register("serial_violations", _serial_violations())
    spark.udf.register("has_cycle", _has_cycle())
