"""Exact one-update-at-a-time maintenance inside one task per root: no shuffle, parallel over roots.

The graph goes to the workers through the shared folder, behind engine.choose()'s size check, and never to the driver; a root copies only the
lists it touches, and its first state comes from whole-array rounds. Counters follow the published measures: residual
updates (repair writes and one per neighbour of a push), push iterations, push cost (degrees of pushed vertices).
"""

from __future__ import annotations

import heapq
import math
import random
import time
import uuid
from collections import deque

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank import engine, schemas
from driftrank.functions import measures


class Pull:
    """Arcs in the order of the vertices that mass arrives at, for rounds in which much of the graph is pushed; made when first asked for."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, kind: str):
        self.arcs, self.lists = (src, dst) if kind == "forward" else (dst, src), None

    def into(self, given: np.ndarray) -> np.ndarray:
        """Sums over the arcs into each vertex of what their other ends give away."""
        if self.lists is None:
            frm, to = self.arcs
            order = np.argsort(to, kind="stable")
            first = np.flatnonzero(np.diff(to[order], prepend=-1))
            self.lists = frm[order], first, to[order[first]]
        far, first, at = self.lists
        out = np.zeros(len(given))
        out[at] = np.add.reduceat(given[far], first)
        return out


def settle(src: np.ndarray, dst: np.ndarray, n: int, root: int, alpha: float, rmax: float, kind: str, pull: Pull | None = None) -> tuple[np.ndarray, np.ndarray, float, np.ndarray]:
    """(est, res, sink, counts) of a push from scratch over arrays of arcs, all active vertices of a round at once.

    counts: residual updates, push iterations.
    """
    est, res, sink, counts = np.zeros(n), np.zeros(n), 0.0, np.zeros(2, np.int64)
    res[root] = 1.0
    deg = np.bincount(src, minlength=n)
    unit = np.maximum(deg, 1)
    limit = rmax * unit if kind == "forward" else np.full(n, rmax)
    frm, to = (src, dst) if kind == "forward" else (dst, src)
    reach = deg if kind == "forward" else np.bincount(dst, minlength=n)
    pull = pull or Pull(src, dst, kind)
    while (on := res > limit).any():
        sent = np.where(on, res, 0.0)
        est += alpha * sent
        cost = int(reach[on].sum())
        if 8 * cost > len(src):
            come = pull.into(sent / unit) if kind == "forward" else pull.into(sent) / unit
        else:
            used = on[frm]
            come = np.bincount(to[used], sent[frm[used]] / unit[src[used]], n)
        res = np.where(on, 0.0, res) + (1 - alpha) * come
        counts += cost, int(on.sum())
        if kind == "forward":
            sink += (1 - alpha) * float(sent[deg == 0].sum())
    return est, res, sink, counts


class Frozen:
    """Arcs (m, 2) as arrays: vertex ids, and the far ends of each vertex's arcs in both directions."""

    def __init__(self, arcs: np.ndarray):
        arcs = np.asarray(arcs, dtype=np.int64).reshape(-1, 2)
        self.ids, at = np.unique(arcs, return_inverse=True)
        at = at.reshape(-1, 2)
        self.src, self.dst = at[:, 0], at[:, 1]
        self.deg = np.bincount(self.src, minlength=len(self.ids))
        self.sides: dict[str, tuple[np.ndarray, np.ndarray]] = {}
        self.pulls: dict[str, Pull] = {}

    def side(self, name: str) -> tuple[np.ndarray, np.ndarray]:
        """Where each vertex's list begins, and all lists; made when first asked for."""
        if name not in self.sides:
            near, far = (self.src, self.dst) if name == "out" else (self.dst, self.src)
            line = np.lexsort((far, near))
            self.sides[name] = (np.searchsorted(near[line], np.arange(len(self.ids) + 1)), self.ids[far[line]])
        return self.sides[name]

    def span(self, side: str, u: int) -> tuple[int, int]:
        i = int(np.searchsorted(self.ids, u))
        if i == len(self.ids) or self.ids[i] != u:
            return 0, 0
        starts = self.side(side)[0]
        return int(starts[i]), int(starts[i + 1])

    def near(self, side: str, u: int) -> list[int]:
        lo, hi = self.span(side, u)
        return self.side(side)[1][lo:hi].tolist()

    def size(self, side: str, u: int) -> int:
        lo, hi = self.span(side, u)
        return hi - lo

    def settle(self, root: int, alpha: float, rmax: float, kind: str) -> tuple[dict, dict, float]:
        """(est, res, sink) of a push from scratch, all active vertices of a round at once."""
        i = int(np.searchsorted(self.ids, root))
        if i == len(self.ids) or self.ids[i] != root:
            return {}, {root: 1.0}, 0.0
        pull = self.pulls.setdefault(kind, Pull(self.src, self.dst, kind))
        est, res, sink, _ = settle(self.src, self.dst, len(self.ids), i, alpha, rmax, kind, pull)
        pick = lambda x: dict(zip(self.ids[x != 0].tolist(), x[x != 0].tolist()))
        return pick(est), pick(res), sink


class Lists(dict):
    """One direction of a Frozen graph as lists that may be changed; a list is copied when first asked for."""

    def __init__(self, base: Frozen, side: str):
        super().__init__()
        self.base, self.side = base, side
        self.due: dict[int, list[tuple[int, int]]] = {}  # changes of lists not yet copied

    def __missing__(self, u: int) -> list[int]:
        self[u] = got = self.base.near(self.side, u)
        for v, op in self.due.pop(u, ()):
            (got.append if op > 0 else got.remove)(v)
        return got

    def change(self, u: int, v: int, op: int) -> None:
        if u in self:
            (self[u].append if op > 0 else self[u].remove)(v)
        else:
            self.due.setdefault(u, []).append((v, op))

    def size(self, u: int) -> int:
        if u in self:
            return len(self[u])
        return self.base.size(self.side, u) + sum(op for _, op in self.due.get(u, ()))


class Local:
    """Push state of one root over a private adjacency; kind 'forward' or 'reverse'.

    ``ready`` starts from whole-array rounds; without it the first push runs in ``order`` too, and is counted.
    """

    def __init__(self, arcs, root: int, alpha: float, rmax: float, kind: str = "forward", order: str = "max_first", signs=(1, -1), ready: bool = False):
        base = arcs if isinstance(arcs, Frozen) else Frozen(list(arcs))
        self.out, self.into = Lists(base, "out"), Lists(base, "into")
        self.root, self.alpha, self.rmax, self.kind, self.order, self.signs = root, alpha, rmax, kind, order, signs
        self.repair_abs = 0.0
        self.updates = self.pushes = self.cost = 0
        if ready:
            self.est, self.res, self.sink = base.settle(root, alpha, rmax, kind)
            self.drain(self.res)
        else:
            self.restart()

    def restart(self) -> None:
        """Push from scratch on the graph as it is now."""
        self.est: dict[int, float] = {}
        self.res = {self.root: 1.0}
        self.sink = 0.0
        self.drain([self.root])

    def limit(self, u: int) -> float:
        return self.rmax * (max(1, self.out.size(u)) if self.kind == "forward" else 1)

    def over(self, u: int, sign: int) -> bool:
        r = self.res.get(u, 0.0) * sign
        return r > self.rmax and r > self.limit(u)

    def push(self, u: int, r: float | None = None) -> list[int]:
        """Push u's residual, or ``r`` of it; the vertices reached."""
        a = self.alpha
        left = self.res.pop(u)
        if r is None:
            r = left
        elif left != r:
            self.res[u] = left - r
        self.est[u] = self.est.get(u, 0.0) + a * r
        near = self.out[u] if self.kind == "forward" else self.into[u]
        if self.kind == "forward":
            if not near:
                self.sink += (1 - a) * r
            share = (1 - a) * r / max(1, len(near))
            for v in near:
                self.res[v] = self.res.get(v, 0.0) + share
        else:
            for v in near:
                self.res[v] = self.res.get(v, 0.0) + (1 - a) * r / self.out.size(v)
        self.updates += len(near)
        self.pushes += 1
        self.cost += len(near)
        return near

    def drain(self, touched) -> None:
        """Push until no residual is over its limit: positive ones first, then negative ones. Only touched vertices can be."""
        seeds = set(touched)
        for sign in self.signs:
            if self.order == "max_first":
                queue = [(-self.res[u] * sign, u) for u in seeds if self.over(u, sign)]
                heapq.heapify(queue)
                while queue:
                    _, u = heapq.heappop(queue)
                    if self.over(u, sign):
                        for v in self.push(u):
                            seeds.add(v)
                            if self.over(v, sign):
                                heapq.heappush(queue, (-self.res[v] * sign, v))
            else:
                line = deque(sorted(u for u in seeds if self.over(u, sign)))
                while line:
                    wave = list(dict.fromkeys(line)) if self.order == "sync" else [line.popleft()]
                    if self.order == "sync":
                        line.clear()
                    # a wave is pushed with the residuals it begins with
                    held = {u: self.res[u] for u in wave if self.over(u, sign)}
                    for u in held:
                        for v in self.push(u, held[u]):
                            seeds.add(v)
                            if self.order == "sync" or self.over(v, sign):
                                line.append(v)
                    if self.order == "sync":
                        line = deque(u for u in line if self.over(u, sign))

    def add(self, v: int, x: float) -> None:
        self.res[v] = self.res.get(v, 0.0) + x
        self.repair_abs += abs(x)
        self.updates += 1

    def arc(self, u: int, v: int, op: int, how: str) -> set[int]:
        """Change arc u -> v (op +1 or -1), repair by ``how`` (lazy, eager or reverse); which vertices were touched."""
        a, e = self.alpha, self.est.get(u, 0.0)
        if self.kind == "reverse":
            self.into.change(v, u, op)
        if e == 0.0 and (self.kind == "forward" or not (u == self.root or self.res.get(u) or self.est.get(v))):
            self.out.change(u, v, op)  # nothing to repair
            return {u}
        old = list(self.out[u]) if how == "eager" else None
        d = self.out.size(u)
        self.out.change(u, v, op)
        new = d + op
        if how == "reverse":
            unit = 1.0 if u == self.root else 0.0
            r = self.res.get(u, 0.0)
            x = e + a * r - a * unit if d else 0.0
            x = (x * d + op * (1 - a) * self.est.get(v, 0.0)) / new if new else 0.0
            self.add(u, (x - e + a * unit) / a - r)
            return {u}
        if d == 0 or new == 0:
            self.sink -= op * (1 - a) / a * e
            self.add(v, op * (1 - a) / a * e)
            return {u, v}
        if how == "lazy":
            rho = e / d
            self.est[u] = rho * new
            self.add(u, -op * rho / a)
            self.add(v, op * (1 - a) / a * rho)
            return {u, v}
        for x in old:
            if op > 0 or x != v:
                self.add(x, (1 - a) / a * e * (1 / new - 1 / d))
        self.add(v, (1 - a) / a * e * (1 / new if op > 0 else -1 / d))
        return {u, v, *old}

    def update(self, arcs: list[tuple[int, int, int]], how: str) -> None:
        touched: set[int] = set()
        for u, v, op in arcs:
            touched |= self.arc(u, v, op, how)
        self.drain(touched)

    def checked_update(self, arcs: list[tuple[int, int, int]], how: str) -> bool:
        """An update of a forward state; whether its push cost kept measures.forward_update_bound()."""
        mass = lambda: sum(map(abs, self.res.values()))
        before, added, cost = mass(), self.repair_abs, self.cost
        self.update(arcs, how)
        bound = measures.forward_update_bound(before, mass(), self.repair_abs - added, self.alpha, self.rmax)
        return self.cost - cost <= bound * (1 + 1e-9) + 1e-6

    def entries(self) -> int:
        return sum(x != 0 for x in self.est.values()) + sum(x != 0 for x in self.res.values())


class Walks:
    """Monte-Carlo baseline: ``r`` walks from one root with an index of visits, rerouted on each arc update.

    Each visit that goes on is rerouted to a new arc with chance 1 / degree. So many visits as stay before the first such one
    are drawn at once, and the visits of a vertex are looked at only if one of them is rerouted.
    """

    def __init__(self, arcs, root: int, alpha: float, r: int, seed: int = 1):
        self.out = Lists(arcs if isinstance(arcs, Frozen) else Frozen(list(arcs)), "out")
        self.alpha, self.root, self.rng = alpha, root, random.Random(seed * 1_000_003 + root)
        self.paths: list[list[int]] = []
        self.at: dict[int, set[int]] = {}
        self.leave: dict[int, int] = {}  # visits of a vertex that go on, or would if it had an arc
        self.rerouted = 0
        for w in range(r):
            self.paths.append([])
            self.put(w, self.grow([root]))

    def grow(self, path: list[int]) -> list[int]:
        """Walk on from the last vertex; a path that cannot leave ends with the mark -1."""
        while self.rng.random() >= self.alpha:
            near = self.out[path[-1]]
            if not near:
                return [*path, schemas.SINK]
            path.append(near[int(self.rng.random() * len(near))])
        return path

    def put(self, w: int, path: list[int], kept: int = 0) -> None:
        """A walk's path from its ``kept``-th vertex on, with the index of it."""
        for x in path[kept:]:
            self.at.setdefault(x, set()).add(w)
        for x in path[max(kept - 1, 0) : -1]:
            self.leave[x] = self.leave.get(x, 0) + 1
        self.paths[w] = path

    def swap(self, w: int, path: list[int], kept: int) -> None:
        """Another path for a walk, the same in its first ``kept`` vertices."""
        was = self.paths[w]
        for x in was[kept - 1 : -1]:
            self.leave[x] -= 1
        for x in set(was[kept:]).difference(was[:kept]):
            self.at[x].discard(w)
        self.put(w, path, kept)
        self.rerouted += 1

    def gap(self, d: int) -> int:
        """Visits of a vertex of degree ``d`` that stay before the next rerouted one."""
        return int(math.log(1.0 - self.rng.random()) / math.log1p(-1 / d)) if d > 1 else 0

    def arc(self, u: int, v: int, op: int) -> None:
        near = self.out[u]
        (near.append if op > 0 else near.remove)(v)
        if not self.leave.get(u):
            return
        if op > 0:
            skip = self.gap(len(near))
            if skip >= self.leave[u]:
                return
            for w in sorted(self.at[u]):
                p = self.paths[w]
                for k in range(len(p) - 1):
                    if p[k] != u:
                        continue
                    if skip == 0:
                        self.swap(w, self.grow([*p[: k + 1], v]), k + 1)
                        skip = self.gap(len(near))
                        break
                    skip -= 1
            return
        for w in sorted(self.at[u]):
            p = self.paths[w]
            for k in range(len(p) - 1):
                if p[k] == u and p[k + 1] == v:
                    self.swap(w, self.grow([*p[: k + 1], near[int(self.rng.random() * len(near))]]) if near else [*p[: k + 1], schemas.SINK], k + 1)
                    break

    def scores(self) -> dict[int, float]:
        out: dict[int, float] = {}
        for p in self.paths:
            if p[-1] != schemas.SINK:
                out[p[-1]] = out.get(p[-1], 0.0) + 1 / len(self.paths)
        return out

    def entries(self) -> int:
        return sum(map(len, self.paths))


TRACE_OUT = "method string, root long, residual_updates long, push_iterations long, push_cost long, repair_abs double, entries long, rerouted long, broken long, seconds double, seq long"
ALL_OUT = f"{TRACE_OUT}, node long, est double, res double"
SHARDS = 2048  # tasks that roots are dealt to, if there are as many; a number given by hand is not merged at run time


def run(initial: DataFrame, events: DataFrame, roots: DataFrame, methods: list[dict], alpha: float = 0.2, undirected: bool = True, batch: int = 1) -> tuple[DataFrame, DataFrame]:
    """Maintain every root over the events with each method; (states, trace). Counters leave out the initial run.

    A method: name, how (lazy, eager, reverse, rebuild_forward, rebuild_reverse, walks), rmax or r, optionally order
    (repairs: sync, side by side for all roots of a task; max_first or fifo, root by root), signs, first (rebuilds only so many updates), check (forward only: counts updates over their cost bound as
    broken) and marks (repairs only: so many further trace rows with the counters up to an update, whose number is seq; the
    row of the whole run has none). ``batch`` updates share one push phase. Both results come from one pass, written to the shared folder.
    Where patches.fits() the states are kept over a stored graph, which neither the driver nor a task holds.
    """
    from driftrank.operators import lockstep, patches, slices

    spark = initial.sparkSession
    who = roots.select(F.col("root").cast("long").alias("root"))
    # tasks keep their roots side by side, so there are no more tasks than run at once
    spread = who.repartition(max(1, min(SHARDS, who.count(), spark.sparkContext.defaultParallelism)), "root")
    names = [c.split()[0] for c in ALL_OUT.split(", ")]

    def told(name: str, root: int, row: dict, est: dict, res: dict):
        rows = [row, *row.pop("marks", [])]
        yield pd.DataFrame([x | {"method": name, "root": root} for x in rows]).reindex(columns=names).convert_dtypes()
        nodes = sorted({*est, *res})
        state = {"node": nodes, "est": [est.get(x, 0.0) for x in nodes], "res": [res.get(x, 0.0) for x in nodes]}
        yield pd.DataFrame(state).assign(method=name, root=root).reindex(columns=names)

    def both_of(shard):
        both_kinds = engine.cut_lineage(spread.mapInPandas(shard, ALL_OUT), "kernel")
        trace = both_kinds.where("seconds is not null").select(*[c.split()[0] for c in TRACE_OUT.split(", ")])
        return both_kinds.where("seconds is null").select("method", "root", "node", "est", "res"), trace

    if patches.fits(initial, events, methods, alpha, undirected, batch):
        folder, files = patches.store(initial, events, undirected)
        follow = max((m.get("first", 1 << 31) for m in methods if m["how"].startswith("rebuild")), default=0)
        seqs = [r["seq"] for r in events.select("seq").orderBy("seq").limit(min(follow, (1 << 31) - 1)).collect()] if follow else []
        end = 2 * (events.agg(F.max("seq")).first()[0] or 0) + 1

        def sparse(parts):
            stored = patches.Stored(folder, files)
            for pdf in parts:
                for r in pdf["root"].astype("int64").tolist():
                    patch = patches.Patch(stored)
                    for m in methods:
                        row, est, res, sink = patches.maintain(patch, r, m, alpha, seqs, end)
                        yield from told(m["name"], r, row, est | {schemas.SINK: sink}, res)
                    stored.parts.clear()  # mapped pages count as the task's memory

        return both_of(sparse)
    if engine.choose(initial.select("src", "dst")) != "kernel" or engine.choose(events) != "kernel":
        raise ValueError("graph over the kernel's checked bound; use operators.push and operators.repair")
    folder = f"{engine.shared_folder(spark)}/graph-{uuid.uuid4().hex}"
    first = slices.keep(initial.select("src", "dst"), folder, "first")
    later = slices.keep((events.orderBy("seq") if "seq" in events.columns else events).select("src", "dst", "op"), folder, "later")

    def one(base: Frozen, both: lockstep.Updates, root: int, m: dict) -> tuple[dict, dict, dict]:
        how, order = m["how"], m.get("order", "max_first")
        kind = "reverse" if how.endswith("reverse") else "forward"
        row = {"residual_updates": 0, "push_iterations": 0, "push_cost": 0, "repair_abs": 0.0, "rerouted": 0, "broken": 0}
        if how == "walks":
            k = Walks(base, root, alpha, m["r"])
            t = time.perf_counter()
            for now in both.batches(1):
                for a in now:
                    k.arc(*a)
            row |= {"seconds": time.perf_counter() - t, "rerouted": k.rerouted, "entries": k.entries()}
            return row, k.scores(), {}
        k = Local(base, root, alpha, m["rmax"], kind, order, m.get("signs", (1, -1)), ready=True)
        u0, p0, c0 = k.updates, k.pushes, k.cost
        t = time.perf_counter()
        marks = []
        step = max(1, len(both) // m["marks"]) if m.get("marks") else len(both) + 1
        for lo, now in zip(range(0, len(both), batch), both.batches(batch), strict=True):
            if m.get("check"):
                row["broken"] += not k.checked_update(now, how)
            else:
                k.update(now, how)
            done = min(lo + batch, len(both))
            if done // step > lo // step:
                marks.append({"seq": done, "residual_updates": k.updates - u0, "push_iterations": k.pushes - p0, "push_cost": k.cost - c0, "seconds": time.perf_counter() - t})
        row["marks"] = marks
        row |= {"seconds": time.perf_counter() - t, "residual_updates": k.updates - u0, "push_iterations": k.pushes - p0, "push_cost": k.cost - c0, "repair_abs": k.repair_abs, "entries": k.entries()}
        return row, k.est | {schemas.SINK: k.sink}, k.res

    def shard(parts):
        base = None
        for pdf in parts:
            if base is None and len(pdf):
                u, v = slices.kept(folder, first, 2)
                two = (u != v) & undirected
                base = Frozen(np.stack((np.concatenate((u, v[two])), np.concatenate((v, u[two]))), 1))
                u, v, op = slices.kept(folder, later, 3)
                both = lockstep.Updates(u, v, op.astype(np.int8), (u != v) & undirected)
            own = pdf["root"].astype("int64").tolist()
            for m in methods:
                if m["how"] in lockstep.REBUILDS or m["how"] in lockstep.HOWS and m.get("order", "sync") == "sync" and not m.get("check"):
                    done = ((row, est | {schemas.SINK: sink}, res) for row, est, res, sink in lockstep.maintain(base, both, own, m, alpha, batch))
                else:
                    done = (one(base, both, r, m) for r in own)
                for r, (row, est, res) in zip(own, done, strict=True):
                    yield from told(m["name"], r, row, est, res)

    return both_of(shard)
