"""Transitive closures. The compact one keeps, per transaction in start order, only the band of those it overlaps: what starts
after it ended is reachable by time, and of what ended before it began nothing is, or there is a cycle."""

from __future__ import annotations

import heapq
import time
from bisect import bisect_left, bisect_right


class Late(Exception):
    """The time allowed is over."""


class Cycle(Exception):
    """The edges hold a cycle; args[0] is its edges where known."""


class Band:
    """Reachability over n transactions sorted by start, s[i] < e[i]. Row i packs the bits of places l[i]..r[i].

    With timed=False every band is the whole range and times play no part.
    """

    def __init__(self, s: list[int], e: list[int], timed: bool = True):
        self.n, self.s, self.e, self.timed = len(s), s, e, timed
        n = self.n
        if timed:
            top, tops = -(1 << 80), []
            for x in e:
                top = max(top, x)
                tops.append(top)
            self.r = [bisect_left(s, e[i]) - 1 for i in range(n)]
            self.l = [bisect_right(tops, s[i]) for i in range(n)]
        else:
            self.r, self.l = [n - 1] * n, [0] * n
        self.row = [0] * n
        self.edge: dict[tuple[int, int], tuple[int, int]] = {}
        self.trail: list = []
        self.looked = 0
        self.stop = float("inf")  # on the monotonic clock

    def cells(self) -> int:
        return sum(r - low + 1 for r, low in zip(self.r, self.l, strict=True))

    def reach(self, i: int, j: int) -> bool:
        if j > self.r[i]:
            return True
        return j >= self.l[i] and bool(self.row[i] >> (j - self.l[i]) & 1)

    def _whole(self, i: int) -> tuple[int, int]:
        """Row i as (bits from place 0, first place from which everything is reachable)."""
        return self.row[i] << self.l[i], self.r[i] + 1

    def build(self, succ: list[set[int]]) -> None:
        """Closure of explicit edges and time, transactions finished in reverse topological order. Raises Cycle."""
        n, state, waves = self.n, [0] * self.n, self._waves()
        for root in range(n):
            if time.monotonic() > self.stop:
                raise Late
            if state[root]:
                continue
            stack = [(root, iter([*succ[root], *waves[root]]))]
            state[root] = 1
            while stack:
                i, it = stack[-1]
                for j in it:
                    if state[j] == 1:
                        at = [k for k, _ in stack]
                        at = at[at.index(j) :]
                        raise Cycle([*zip(at, at[1:], strict=False), (i, j)])
                    if not state[j]:
                        state[j] = 1
                        stack.append((j, iter([*succ[j], *waves[j]])))
                        break
                else:
                    stack.pop()
                    state[i] = 2
                    self._finish(i, succ[i], waves[i])

    def _finish(self, i: int, succ: set[int], wave: range) -> None:
        """Row i from the rows of what follows it; a pair keeps an explicit edge of its path."""
        low, r = self.l[i], self.r[i]
        band = (1 << (r - low + 1)) - 1
        for j in [*succ, *wave]:
            more, far = self._whole(j)
            explicit = j in succ
            if explicit:
                more |= 1 << j
                if far <= r:
                    more |= ((1 << (r + 1)) - 1) ^ ((1 << max(far, low)) - 1)
            if more & ((1 << low) - 1) or explicit and far < low:
                raise Cycle([])  # something that ended before i began comes after it
            new = more >> low & band & ~self.row[i]
            self.row[i] |= new
            while new:
                k = (new & -new).bit_length() - 1 + low
                if k == i:
                    raise Cycle([])
                self.edge[i, k] = (i, j) if explicit else self.edge[j, k]
                new &= new - 1

    def _waves(self) -> list[range]:
        """First transactions after each one by time: those that begin before any later one has ended."""
        n = self.n
        if not self.timed:
            return [range(0)] * n
        least = [1 << 80] * (n + 1)
        for i in range(n - 1, -1, -1):
            least[i] = min(least[i + 1], self.e[i])
        return [range(r + 1, bisect_left(self.s, least[r + 1])) if r + 1 < n else range(0) for r in self.r]

    def insert(self, u: int, v: int) -> bool:
        """Adds edge (u, v): False where it was implied, Cycle where v reaches u; else rows in both bands are updated."""
        if u != v and self.reach(u, v):
            return False
        if u == v or self.reach(v, u):
            raise Cycle([(u, v)])
        more, far = self._whole(v)
        more |= 1 << v
        for p in range(self.l[v], self.r[u] + 1):  # others reach v by time already, or can't reach u
            self.looked += 1
            if p != u and not self.reach(p, u) or self.reach(p, v):
                continue
            low, r = self.l[p], self.r[p]
            bits = more
            if far <= r:
                bits |= ((1 << (r + 1)) - 1) ^ ((1 << max(far, low)) - 1)
            new = bits >> low & ((1 << (r - low + 1)) - 1) & ~self.row[p]
            if not new:
                continue
            self.trail.append((p, self.row[p], new))
            self.row[p] |= new
            while new:
                k = (new & -new).bit_length() - 1
                self.edge[p, k + low] = (u, v)
                new &= new - 1
        return True

    def mark(self) -> int:
        return len(self.trail)

    def rollback(self, mark: int) -> None:
        while len(self.trail) > mark:
            p, row, new = self.trail.pop()
            self.row[p] = row
            while new:
                k = (new & -new).bit_length() - 1
                self.edge.pop((p, k + self.l[p]), None)
                new &= new - 1

    def path(self, i: int, j: int) -> list[tuple[int, int]]:
        """Explicit edges along a path from i to j, in order; hops between them are by time."""
        out, todo = [], [(i, j, False)]
        while todo:
            a, b, explicit = todo.pop()
            if explicit:
                out.append((a, b))
            elif a != b and b <= self.r[a]:
                u, v = self.edge[a, b]
                todo += [(v, b, False), (u, v, True), (a, u, False)] if (a, b) != (u, v) else [(u, v, True)]
        return out


class DictBand(Band):
    """The same closure with a hash map of sets in place of packed rows, for comparison."""

    def __init__(self, s, e, timed: bool = True):
        super().__init__(s, e, timed)
        self.row = _Sets(self.n)


class _Sets:
    """Rows of bits kept as sets of places in a dictionary."""

    def __init__(self, n: int):
        self.of: dict[int, set[int]] = {}

    def __getitem__(self, i: int) -> int:
        return sum(1 << k for k in self.of.get(i, ()))

    def __setitem__(self, i: int, bits: int) -> None:
        at = set()
        while bits:
            at.add((bits & -bits).bit_length() - 1)
            bits &= bits - 1
        self.of[i] = at


def schedule(s: list[int], e: list[int], edges: list[tuple[int, int]]) -> tuple[list[int], list[tuple[int, int, str]]]:
    """(an order of all transactions that keeps edges and time, []), or ([], a cycle as (from, to, "edge" or "time")).

    Time edges go through a chain of all begins and ends, so there are as many as transactions.
    """
    n = len(s)
    events = sorted([(x, 0, i) for i, x in enumerate(e)] + [(x, 1, i) for i, x in enumerate(s)])  # an end comes before a begin at the same time
    succ: list[list[int]] = [[] for _ in range(n + len(events))]
    for k, (_, begin, i) in enumerate(events):
        if k + 1 < len(events):
            succ[n + k].append(n + k + 1)
        if begin:
            succ[n + k].append(i)
        else:
            succ[i].append(n + k)
    for u, v in edges:
        succ[u].append(v)
    need = [0] * len(succ)
    for out in succ:
        for v in out:
            need[v] += 1
    rank = lambda x: (s[x], x) if x < n else (events[x - n][0], x)
    ready = [(rank(x), x) for x in range(len(succ)) if not need[x]]
    heapq.heapify(ready)
    order, done = [], 0
    while ready:
        _, x = heapq.heappop(ready)
        done += 1
        if x < n:
            order.append(x)
        for v in succ[x]:
            need[v] -= 1
            if not need[v]:
                heapq.heappush(ready, (rank(v), v))
    if done == len(succ):
        return order, []
    before: dict[int, int] = {}
    for x, out in enumerate(succ):
        if need[x] or any(need[v] for v in out):
            for v in out:
                if need[v] and need[x]:
                    before[v] = x
    x, seen = next(v for v in before if need[v]), []
    while x not in seen:
        seen.append(x)
        x = before[x]
    ring = [*reversed(seen[seen.index(x) :])]
    start = next(k for k, y in enumerate(ring) if y < n)
    ring = [*ring[start:], *ring[:start], ring[start]]
    out, last, hop = [], ring[0], "edge"
    for y in ring[1:]:
        if y >= n:
            hop = "time"
        else:
            out.append((last, y, hop))
            last, hop = y, "edge"
    return [], out


def adjacent(n: int, edges: list[tuple[int, int]]) -> list[int]:
    """Edges as bit rows."""
    row = [0] * n
    for u, v in edges:
        row[u] |= 1 << v
    return row


def by_time(s: list[int], e: list[int]) -> tuple[list[int], list[int]]:
    """All time edges of transactions in start order as bit rows and as bit columns, without making them one by one."""
    n = len(s)
    full, row, col, upto, k = (1 << n) - 1, [], [], 0, 0
    ends = sorted(range(n), key=e.__getitem__)
    for i in range(n):
        first = bisect_left(s, e[i])
        row.append(full >> first << first)
        while k < n and e[ends[k]] <= s[i]:
            upto |= 1 << ends[k]
            k += 1
        col.append(upto)
    return row, col


def purdom_rows(succ: list[int]) -> list[int]:
    """Full closure of successors given as bit rows, in reverse topological order. A successor that another one reaches adds
    nothing and is passed over. Raises Cycle."""
    n = len(succ)
    row, new, open_ = [0] * n, (1 << n) - 1, 0
    for root in range(n):
        if not new >> root & 1:
            continue
        stack = [root]
        new ^= 1 << root
        open_ |= 1 << root
        while stack:
            i = stack[-1]
            if succ[i] & open_:
                raise Cycle([])
            todo = succ[i] & new
            if todo:
                j = (todo & -todo).bit_length() - 1
                stack.append(j)
                new ^= 1 << j
                open_ |= 1 << j
                continue
            stack.pop()
            open_ ^= 1 << i
            got = rest = succ[i]
            while rest:
                j = (rest & -rest).bit_length() - 1
                got |= row[j]
                rest &= ~(row[j] | 1 << j)
            row[i] = got
    return row


def purdom(n: int, edges: list[tuple[int, int]]) -> list[int]:
    """Full closure of edges as bit rows. Raises Cycle."""
    return purdom_rows(adjacent(n, edges))


def warshall_rows(succ: list[int]) -> list[int]:
    row = list(succ)
    n = len(row)
    for k in range(n):
        bit, more = 1 << k, row[k]
        for i in range(n):
            if row[i] & bit:
                row[i] |= more
    if any(row[i] >> i & 1 for i in range(n)):
        raise Cycle([])
    return row


def warshall(n: int, edges: list[tuple[int, int]]) -> list[int]:
    return warshall_rows(adjacent(n, edges))


class Full:
    """Reachability over all pairs as bit rows and bit columns, grown edge by edge."""

    def __init__(self, n: int, row: list[int] | None = None, col: list[int] | None = None):
        self.row, self.col = list(row or [0] * n), list(col or [0] * n)

    def insert(self, u: int, v: int) -> None:
        row, col = self.row, self.col
        if row[u] >> v & 1:
            return
        if u == v or row[v] >> u & 1:
            raise Cycle([(u, v)])
        more = row[v] | 1 << v
        before = (col[u] | 1 << u) & ~col[v]
        while before:
            p = (before & -before).bit_length() - 1
            before &= before - 1
            new, bit = more & ~row[p], 1 << p
            row[p] |= new
            while new:
                k = (new & -new).bit_length() - 1
                col[k] |= bit
                new &= new - 1


def italiano_rows(succ: list[int]) -> list[int]:
    """Full closure edge by edge, from the last row's edges to the first one's; edges that are implied by then are passed over."""
    f = Full(len(succ))
    for u in range(len(succ) - 1, -1, -1):
        rest = succ[u]
        while rest:
            f.insert(u, (rest & -rest).bit_length() - 1)
            rest &= ~f.row[u]
    return f.row


def italiano(n: int, edges: list[tuple[int, int]]) -> list[int]:
    """Full closure, edge by edge."""
    f = Full(n)
    for u, v in edges:
        f.insert(u, v)
    return f.row


def by_rebuilding(n: int, edges: list[tuple[int, int]], batch: int) -> list[int]:
    """The closure made anew after each batch of edges."""
    row = [0] * n
    for k in range(0, max(1, len(edges)), batch):
        row = warshall(n, edges[: k + batch])
    return row
