"""Maintenance of many roots side by side: each update is applied once, its repair and pushes are array operations over all roots.

The push order is synchronous: all active (root, vertex) pairs of a round are pushed with the residuals they had when it
began. States are dense, vertices x roots; the kernel deals the roots so that they stay under a fixed number of cells.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from itertools import islice

import numpy as np

from driftrank.operators.kernel import Frozen, Pull, settle

HOWS = ("lazy", "eager", "reverse")
REBUILDS = ("rebuild_forward", "rebuild_reverse")  # from scratch after each of the first updates
CELLS = 1 << 23  # roots times vertices of one group: two arrays of 64 MB


def spans(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """begin[0] .. begin[0] + size[0] - 1, then the same of each following pair."""
    ends = np.cumsum(size)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(begin - ends + size, size)


class Updates:
    """Changes of edges in their order, as arrays: ends, op, and whether the arc back changes with the arc. Arcs are named when their turn comes."""

    CHUNK = 1 << 16  # updates that are named at once

    def __init__(self, u: np.ndarray, v: np.ndarray, op: np.ndarray, back: np.ndarray):
        self.u, self.v, self.op, self.back = u, v, op, back

    @classmethod
    def of(cls, both) -> Updates:
        """From the arcs of each update: u -> v, and v -> u or no other."""
        if isinstance(both, Updates):
            return both
        rows = np.array([a[0] for a in both], np.int64).reshape(-1, 3)
        return cls(rows[:, 0], rows[:, 1], rows[:, 2].astype(np.int8), np.array([len(a) > 1 for a in both], bool))

    def __len__(self) -> int:
        return len(self.u)

    def among(self, ids: np.ndarray) -> Updates:
        """The same with places in ``ids`` for vertices."""
        return Updates(*(np.searchsorted(ids, x).astype(np.int32) for x in (self.u, self.v)), self.op, self.back)

    def more(self) -> tuple[np.ndarray, np.ndarray]:
        """(sources, heads) of all arcs that are added."""
        new = self.op > 0
        two = new & self.back
        return np.concatenate((self.u[new], self.v[two])), np.concatenate((self.v[new], self.u[two]))

    def batches(self, size: int) -> Iterator[list[tuple[int, int, int]]]:
        """Arcs of each ``size`` updates."""
        step = max(1, self.CHUNK // size) * size
        for lo in range(0, len(self), step):
            arcs = [(((u, v, op), (v, u, op)) if back else ((u, v, op),)) for u, v, op, back in zip(*(x[lo : lo + step].tolist() for x in (self.u, self.v, self.op, self.back)), strict=True)]
            for i in range(0, len(arcs), size):
                yield [a for pair in arcs[i : i + size] for a in pair]


class Side:
    """Changing adjacency lists of one direction in one array; a list has room for all arcs that the events will bring."""

    def __init__(self, near: np.ndarray, far: np.ndarray, more: np.ndarray, n: int):
        self.deg = np.bincount(near, minlength=n)
        room = self.deg + np.bincount(more, minlength=n)
        self.start = np.cumsum(room) - room
        self.far = np.empty(int(room.sum()), np.int64)
        line = np.lexsort((far, near))
        self.far[spans(self.start, self.deg)] = far[line]

    def near(self, u: int) -> np.ndarray:
        return self.far[self.start[u] : self.start[u] + self.deg[u]]

    def change(self, u: int, v: int, op: int) -> None:
        if op > 0:
            self.far[self.start[u] + self.deg[u]] = v
        else:
            own = self.near(u)
            own[np.flatnonzero(own == v)[0]] = own[-1]
        self.deg[u] += op


class Lockstep:
    """Push states of several roots (vertex numbers) over one graph of ``n`` vertices; ``more``: sources and heads of arcs to come.

    A vertex's numbers of all roots lie side by side (vertices x roots), so an update reads and writes whole rows.
    """

    def __init__(self, src: np.ndarray, dst: np.ndarray, n: int, roots: np.ndarray, more: tuple[np.ndarray, np.ndarray], alpha: float, rmax: float, kind: str, signs=(1, -1)):
        self.out = Side(src, dst, more[0], n)
        self.into = Side(dst, src, more[1], n) if kind == "reverse" else None
        self.n, self.k, self.roots, self.alpha, self.rmax, self.kind, self.signs = n, len(roots), roots, alpha, rmax, kind, signs
        self.est, self.res, self.sink = np.zeros((n, self.k)), np.zeros((n, self.k)), np.zeros(self.k)
        pull = Pull(src, dst, kind)
        for i, r in enumerate(roots.tolist()):
            self.est[:, i], self.res[:, i], self.sink[i], _ = settle(src, dst, n, r, alpha, rmax, kind, pull)
        del pull
        self.unit = {r: (roots == r) * 1.0 for r in roots.tolist()}
        self.limit = rmax * np.maximum(self.out.deg, 1.0) if kind == "forward" else np.full(n, rmax)
        self.updates, self.pushes, self.cost = (np.zeros(self.k, np.int64) for _ in range(3))
        self.repair_abs = np.zeros(self.k)
        self.flat_est, self.flat_res = self.est.reshape(-1), self.res.reshape(-1)

    def restart(self) -> None:
        """Push all roots from scratch on the graph as it is now."""
        for x in (self.est, self.res, self.sink):
            x[:] = 0.0
        self.flat_res[(at := self.roots * self.k + np.arange(self.k))] = 1.0
        self.drain(at, (1,))

    def change(self, u: int, v: int, op: int) -> None:
        self.out.change(u, v, op)
        if self.into is not None:
            self.into.change(v, u, op)
        else:
            self.limit[u] = self.rmax * max(int(self.out.deg[u]), 1)

    def over(self, pairs: np.ndarray, sign: int) -> np.ndarray:
        """Those of the pairs (vertex * roots + number of the root) whose residual is over its limit in the given direction."""
        if 4 * len(pairs) > self.n * self.k:  # no others can be over it, so a look at all finds the same
            return np.flatnonzero(self.res * sign > self.limit[:, None])
        pairs = pairs[self.flat_res[pairs] * sign > self.limit[pairs // self.k]]
        return np.unique(pairs) if len(pairs) > 1 else pairs

    def drain(self, touched: np.ndarray, signs=None) -> None:
        """Rounds until no residual is over its limit; only touched pairs can be over it when this is called."""
        a, k, side = self.alpha, self.k, self.out if self.kind == "forward" else self.into
        for sign in signs or self.signs:
            now = self.over(touched, sign)
            while len(now):
                u, who = np.divmod(now, k)
                r = self.flat_res[now]
                self.flat_est[now] += a * r
                self.flat_res[now] = 0.0
                d = side.deg[u]
                far = side.far[spans(side.start[u], d)]
                if self.kind == "forward":
                    share = np.repeat((1 - a) * r / np.maximum(d, 1), d)
                    if not d.all():
                        np.add.at(self.sink, who[d == 0], (1 - a) * r[d == 0])
                else:
                    share = np.repeat((1 - a) * r, d) / self.out.deg[far]
                to = far * k + np.repeat(who, d)
                np.add.at(self.flat_res, to, share)
                sent = np.bincount(who, d, k).astype(np.int64)
                self.updates += sent
                self.cost += sent
                self.pushes += np.bincount(who, minlength=k)
                now = self.over(to, sign)

    def add(self, v: int, x: np.ndarray, hit: np.ndarray) -> None:
        """x, which is zero where not ``hit``, to the residuals of vertex v."""
        self.res[v] += x
        self.repair_abs += np.abs(x)
        self.updates += hit

    def arc(self, u: int, v: int, op: int, how: str) -> tuple[list[int], np.ndarray | None]:
        """Change arc u -> v (op +1 or -1) and repair all states by ``how`` (lazy, eager or reverse); the touched vertices."""
        a, e = self.alpha, self.est[u]
        d = int(self.out.deg[u])
        new = d + op
        if how == "reverse":
            unit, head, r = self.unit.get(u, 0.0), self.est[v], self.res[u]
            hit = (e != 0) | (r != 0) | (head != 0) | (unit > 0)
            self.change(u, v, op)
            x = e + a * r - a * unit if d else np.zeros(self.k)
            x = (x * d + op * (1 - a) * head) / new if new else np.zeros(self.k)
            self.add(u, np.where(hit, (x - e + a * unit) / a - r, 0.0), hit)
            return [u], None
        hit = e != 0
        old = self.out.near(u) if how == "eager" and d and new else None
        if old is not None and op < 0:
            old = old[old != v]
        self.change(u, v, op)
        if not hit.any():
            return [u], None  # a lower degree alone lowers limits
        if d == 0 or new == 0:
            self.sink -= op * (1 - a) / a * e
            self.add(v, op * (1 - a) / a * e, hit)
        elif how == "lazy":
            rho = e / d
            self.est[u] = rho * new
            self.add(u, -op * rho / a, hit)
            self.add(v, op * (1 - a) / a * rho, hit)
        else:
            moved = (1 - a) / a * e * (1 / new - 1 / d)
            self.res[old] += moved  # heads of a vertex are distinct
            self.repair_abs += np.abs(moved) * len(old)
            self.updates += hit * len(old)
            self.add(v, (1 - a) / a * e * (1 / new if op > 0 else -1 / d), hit)
        return [u, v], old

    def update(self, arcs: list[tuple[int, int, int]], how: str) -> None:
        rows, lists = [], []
        for u, v, op in arcs:
            ends, old = self.arc(u, v, op, how)
            rows += ends
            if old is not None:
                lists.append(old)
        rows = np.concatenate([np.array(rows, np.int64), *lists])
        at, who = np.nonzero(np.abs(self.res[rows]) > self.limit[rows][:, None])
        if len(at):
            self.drain(rows[at] * self.k + who)


def maintain(base: Frozen, both: Updates | list, roots: list[int], m: dict, alpha: float, batch: int = 1):
    """Per root (in order): (counters, est, res) as the kernel's one-root form gives them. ``both``: arcs of each update.

    Roots are taken in groups of CELLS cells; a root's seconds are its share of its group's.
    """
    how = m["how"]
    kind = "reverse" if how.endswith("reverse") else "forward"
    both = Updates.of(both)
    ids = np.unique(np.concatenate((base.ids, np.array(roots, np.int64), both.u, both.v)))
    n = len(ids)
    place = np.searchsorted(ids, base.ids)
    src, dst = place[base.src], place[base.dst]
    todo = both.among(ids)
    step = max(1, len(both) // m["marks"]) if m.get("marks") else len(both) + 1
    group = max(1, CELLS // max(n, 1))
    for lo in range(0, len(roots), group):
        own = np.searchsorted(ids, np.array(roots[lo : lo + group], np.int64))
        k = Lockstep(src, dst, n, own, todo.more(), alpha, m["rmax"], kind, m.get("signs", (1, -1)))
        marks = []
        t = time.perf_counter()

        def counters(k=k, t=t, size=len(own)):
            return k.updates.copy(), k.pushes.copy(), k.cost.copy(), (time.perf_counter() - t) / size

        rebuilt = how in REBUILDS
        for now in islice(todo.batches(1), m.get("first")) if rebuilt else ():
            for x in now:
                k.change(*x)
            k.restart()
        for b, now in enumerate(() if rebuilt else todo.batches(batch)):
            k.update(now, how)
            done = min((b + 1) * batch, len(todo))
            if done // step > b * batch // step:
                marks.append((done, counters()))
        end = counters()
        for i in range(len(own)):
            told = lambda c, i=i: {"residual_updates": int(c[0][i]), "push_iterations": int(c[1][i]), "push_cost": int(c[2][i]), "seconds": c[3]}
            est, res = ({int(ids[x]): float(a[x]) for x in np.flatnonzero(a)} for a in (k.est[:, i], k.res[:, i]))
            row = told(end) | {"repair_abs": float(k.repair_abs[i]), "entries": len(est) + len(res), "rerouted": 0, "broken": 0}
            yield row | {"marks": [told(c) | {"seq": s} for s, c in marks]}, est, res, float(k.sink[i])
