"""Search for choices that keep the graph acyclic, driven by conflicts.

A constraint is a list of options, an option a list of edges (u, v, via): via is None, or the pair of transactions whose order
makes the edge hold. Exactly one option holds. Edges go into a closure that can be rolled back; every edge remembers the choices it
rests on, so a cycle names the choices that can't hold together, which is learned and tells how far to go back.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from orderproof.functions.closure import Band, Cycle, DictBand, Late, schedule


@dataclass
class Outcome:
    ok: bool | None  # None: out of time
    reason: str = ""
    cycle: list = field(default_factory=list)
    chosen: dict = field(default_factory=dict)
    left: int = 0  # constraints that pruning didn't settle
    conflicts: int = 0
    decisions: int = 0
    order: list = field(default_factory=list)


class Conflict(Exception):
    """args[0]: the choices that clash, as a set of (constraint, option)."""


class Search:
    def __init__(self, closure: Band, constraints: list[list[list[tuple]]], known: list[tuple[int, int]], budget_s: float = 600.0, time_first: bool = True, prune: bool = True):
        self.c, self.cons, self.budget, self.time_first, self.prune = closure, constraints, budget_s, time_first, prune
        self.why: dict[tuple[int, int], frozenset] = {e: frozenset() for e in known}
        self.chosen: dict[int, int] = {}
        self.reason: dict[int, frozenset] = {}  # of a forced choice
        self.waiting: list[tuple[int, tuple]] = []  # open edges of chosen options
        self.learned: list[frozenset] = []
        self.conflicts = self.decisions = 0
        self.log: list[tuple[dict, object]] = []  # keys that were added, to be taken back
        self.facts = False  # while pruning: what is forced then rests on no choice
        self.clash: list[tuple[int, int]] = []  # the last cycle met: explicit edges in order
        self.stop = time.monotonic() + budget_s

    def support(self, i: int, j: int) -> frozenset:
        """Choices that a path from i to j rests on."""
        if self.facts:
            return frozenset()
        out: set = set()
        for e in self.c.path(i, j):
            out |= self.why[e]
        return frozenset(out)

    def put(self, where: dict, key, value) -> None:
        where[key] = value
        self.log.append((where, key))

    def add(self, u: int, v: int, because: frozenset) -> None:
        if u == v or self.c.reach(v, u):
            self.clash = [(u, v), *self.c.path(v, u)] if u != v else [(u, v)]
            raise Conflict(because | self.support(v, u) if u != v else because)
        if not self.c.reach(u, v):
            self.put(self.why, (u, v), because)
            self.c.insert(u, v)

    def choose(self, k: int, o: int, reason: frozenset | None) -> None:
        self.put(self.chosen, k, o)
        if reason is not None:
            self.put(self.reason, k, reason)
        mine = frozenset() if self.facts else frozenset([(k, o)])
        for u, v, via in self.cons[k][o]:
            if via is None:
                self.add(u, v, mine)
            else:
                self.waiting.append((k, (u, v, via)))

    def settle(self) -> bool:
        """Open edges of chosen options whose via pair has an order by now."""
        moved = False
        for k, (u, v, (m, n)) in list(self.waiting):
            if self.c.reach(m, n):
                if not self.c.reach(u, v):
                    self.add(u, v, frozenset() if self.facts else frozenset([(k, self.chosen[k])]) | self.support(m, n))
                    moved = True
        return moved

    def blocked(self, k: int, o: int) -> frozenset | None:
        """Why an option can't hold now, or None."""
        for u, v, via in self.cons[k][o]:
            if u == v and via is None:
                return frozenset()
            if (via is None or self.c.reach(*via)) and self.c.reach(v, u):
                self.clash = [(u, v), *self.c.path(v, u)]
                return self.support(v, u) | (self.support(*via) if via else frozenset())
        mine = (k, o)
        for clash in self.learned:
            if mine in clash and all(self.chosen.get(a) == b for a, b in clash if (a, b) != mine):
                return clash - {mine}
        return None

    def propagate(self) -> None:
        """Options that can't hold go; the last one left is chosen."""
        moved = True
        while moved:
            moved = self.settle()
            if time.monotonic() > self.stop:
                raise Late
            for k in range(len(self.cons)):
                if k in self.chosen:
                    continue
                out, free = frozenset(), []
                for o in range(len(self.cons[k])):
                    bad = self.blocked(k, o)
                    if bad is None:
                        free.append(o)
                        if len(free) > 1:
                            break
                    else:
                        out |= bad
                if not free:
                    raise Conflict(out)
                if len(free) == 1 and len(self.cons[k]) > 0:
                    self.choose(k, free[0], out)
                    moved = True

    def decided(self, clash: frozenset) -> frozenset:
        """The clash in terms of decisions: forced choices are replaced by what forced them."""
        out, todo, seen = set(), list(clash), set()
        while todo:
            k, o = todo.pop()
            if (k, o) in seen:
                continue
            seen.add((k, o))
            if k in self.reason:
                todo += list(self.reason[k])
            else:
                out.add((k, o))
        return frozenset(out)

    def run(self) -> Outcome:
        levels: list[tuple] = []  # (constraint, option, marks before)

        def done(ok, why="") -> Outcome:
            return Outcome(ok, why, [] if ok or ok is None else self.clash, dict(self.chosen), self.left, self.conflicts, self.decisions)

        self.left = len(self.cons)
        try:
            if self.prune:
                self.facts = True
                self.propagate()
                self.facts = False
        except Conflict:
            return done(False, "forced_conflict")
        self.left = len(self.cons) - len(self.chosen)
        base = self._save()
        pending: list[tuple] = []
        while True:
            try:
                for k, o in pending:
                    levels.append((k, o, self._save()))
                    pending = []
                    self.decisions += 1
                    self.choose(k, o, None)
                self.propagate()
                todo = [k for k in range(len(self.cons)) if k not in self.chosen]
                if not todo:
                    return done(True)
                pending = [self._pick(todo)]
            except Conflict as x:
                self.conflicts += 1
                if time.monotonic() > self.stop:
                    return done(None, "timeout")
                pending = []
                clash = self.decided(x.args[0])
                at = [d for d, (k, o, _) in enumerate(levels) if (k, o) in clash]
                if not at:
                    return done(False, "unsat")
                self.learned.append(clash)
                keep = at[-2] + 1 if len(at) > 1 else 0  # back to the second deepest decision of the clash
                self._restore(levels[keep][2] if keep < len(levels) else base)
                del levels[keep:]
                if not levels:
                    self._restore(base)

    def _pick(self, todo: list[int]) -> tuple[int, int]:
        k = min(todo, key=lambda k: len(self.cons[k]))
        free = [o for o in range(len(self.cons[k])) if self.blocked(k, o) is None]
        if self.time_first:  # what began and ended earlier is tried first
            mid = lambda o: min((self.c.s[u] + self.c.e[u] for u, _, _ in self.cons[k][o]), default=0)
            free.sort(key=mid)
        return k, free[0]

    def _save(self) -> tuple:
        return self.c.mark(), len(self.log), len(self.waiting)

    def _restore(self, saved: tuple) -> None:
        mark, log, waiting = saved
        self.c.rollback(mark)
        while len(self.log) > log:
            where, key = self.log.pop()
            del where[key]
        del self.waiting[waiting:]


def ring(cycle: list[tuple[int, int]]) -> list[tuple[int, int, str]]:
    """Explicit edges of a cycle in order, with the hops by time between them."""
    out = []
    for (u, v), (w, _) in zip(cycle, [*cycle[1:], *cycle[:1]], strict=True):
        out.append((u, v, "edge"))
        if v != w:
            out.append((v, w, "time"))
    return out


def solve(
    s: list[int], e: list[int], known: list[tuple[int, int]], constraints: list[list[list[tuple]]], timed: bool = True, budget_s: float = 600.0, time_first: bool = True, prune: bool = True, layout: str = "bits"
) -> Outcome:
    """Decides a set of transactions sorted by start. known: certain edges; constraints: see Search. An accepted one comes with an
    order, a rejected one with a cycle (u, v, "edge" or "time"): of known edges, or the last one that left no choice."""
    c = {"bits": Band, "dict": DictBand}[layout](s, e, timed)
    c.stop = time.monotonic() + budget_s
    succ = [set() for _ in s]
    for u, v in known:
        if u == v:
            return Outcome(False, "known_cycle", [(u, v, "edge")])
        succ[u].add(v)
    when = (s, e) if timed else ([0] * len(s), [1] * len(s))
    try:
        c.build(succ)
        if any(not options for options in constraints):
            return Outcome(False, "empty_candidates")
        search = Search(c, constraints, known, budget_s, time_first, prune)
        search.stop = c.stop
        out = search.run()
    except Cycle:
        return Outcome(False, "known_cycle", schedule(*when, known)[1])
    except Late:
        return Outcome(None, "timeout")
    if out.ok:
        out.order = schedule(*when, list(search.why))[0]
    out.cycle = ring(out.cycle)
    return out
