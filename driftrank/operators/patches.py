"""Maintenance of sparse states over a stored graph that only grows: no task, and not the driver, holds the graph.

All arcs, now and to come, are kept in the shared folder as files of vertices, each vertex's arcs in the order of their
arrival. So the list of a vertex at any time is the beginning of its stored list, and nothing is ever changed. A root
reads only the lists of vertices that its state reaches, and sees only the updates at vertices with an estimate: all
others leave its state as it is (reverse: they shrink residuals by a known factor, which is applied and counted when
such a residual is next used). For thresholds that keep the states small against the graph; see kernel.run().
"""

from __future__ import annotations

import heapq
import os
import re
import time
import uuid
from collections import deque

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank import engine
from driftrank.functions import measures
from driftrank.operators.lockstep import spans

HOWS = ("lazy", "eager", "reverse", "rebuild_forward", "rebuild_reverse")
PART = 1_000_000  # arcs of a file, about
OLD = -(1 << 62)  # the time of arcs of the initial graph
BEGIN = -1  # before all updates


def _place(folder: str) -> tuple[pafs.FileSystem, str]:
    if re.match(r"(?!file:)\w+://", folder):
        return pafs.FileSystem.from_uri(folder)
    return pafs.LocalFileSystem(), re.sub(r"^file:/+", "/", folder)


def store(initial: DataFrame, events: DataFrame, undirected: bool) -> tuple[str, int]:
    """(folder, number of files) with the arcs of ``initial`` and of ``events`` (seq, src, dst), by vertex and arrival.

    The arc of update s arrives at 2 s, its other way at 2 s + 1.
    """
    spark = initial.sparkSession
    arcs = initial.select("src", "dst", F.lit(OLD).alias("t")).union(events.select("src", "dst", (F.col("seq") * 2).cast("long")))
    if undirected:
        back = F.when(F.col("t") == OLD, F.col("t")).otherwise(F.col("t") + 1)
        arcs = arcs.union(arcs.where("src <> dst").select("dst", "src", back))
    files = max(1, -(-arcs.count() // PART))
    folder = f"{engine.shared_folder(spark)}/arcs-{uuid.uuid4().hex}"

    def write(batches):
        cols = [[], [], []]
        for b in batches:
            for c, x in zip(cols, b.columns[1:]):
                c.append(x.to_numpy(zero_copy_only=False))
        if not cols[0]:
            return
        u, v, t = (np.concatenate(c) for c in cols)
        cols.clear()
        order = np.lexsort((v, t, u))  # a file's arcs are held here anyway
        u, v, t = u[order], v[order], t[order]
        ids, begin = np.unique(u, return_index=True)
        fs, at = _place(folder)
        fs.create_dir(at, recursive=True)
        name = f"{at}/{int(ids[0] >> 3) % files}"
        tmp = f"{name}-{TaskContext.get().taskAttemptId()}"
        with fs.open_output_stream(tmp) as out:
            for x in (np.array([len(ids), len(u)]), ids, np.append(begin, len(u)), t, v):
                out.write(x.astype(np.int64).tobytes())
        fs.move(tmp, name)
        yield pa.RecordBatch.from_arrays([pa.array([len(u)], pa.int64())], ["n"])

    slot = F.pmod(F.shiftright("src", 3), F.lit(files)).cast("int")
    # a file a partition, by number and not by its hash
    keyed = arcs.select(slot.alias("slot"), F.col("src").cast("long"), F.col("dst").cast("long"), "t")
    dealt = keyed.repartitionById(files, F.col("slot"))
    dealt.mapInArrow(write, "n long").agg(F.sum("n")).collect()
    return folder, files


class Stored:
    """Reads lists from the files of store(); a local folder is mapped, another is read file by file."""

    def __init__(self, folder: str, files: int):
        self.folder, self.files, self.parts = folder, files, {}

    def part(self, k: int) -> tuple[np.ndarray, ...]:
        if k not in self.parts:
            fs, at = _place(self.folder)
            name = f"{at}/{k}"
            if isinstance(fs, pafs.LocalFileSystem):
                raw = np.memmap(name, np.int64, "r") if os.path.exists(name) else np.zeros(3, np.int64)
            elif fs.get_file_info(name).type == pafs.FileType.NotFound:
                raw = np.zeros(3, np.int64)
            else:
                with fs.open_input_file(name) as f:
                    raw = np.frombuffer(f.read(), np.int64)
            n, m = int(raw[0]), int(raw[1])
            self.parts[k] = tuple(np.split(raw[2:], np.cumsum([n, n + 1, m])))
        return self.parts[k]

    def read(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(ids in the order of the rest, sizes, times, heads) of all arcs from ``ids``."""
        slot = (ids >> 3) % self.files
        ids = ids[np.argsort(slot, kind="stable")]
        sizes, when, far = [], [], []
        for k in np.unique(slot).tolist():
            own = ids[(ids >> 3) % self.files == k]
            known, begin, t, v = self.part(k)
            if not len(known):
                sizes.append(np.zeros(len(own), np.int64))
                continue
            i = np.minimum(np.searchsorted(known, own), len(known) - 1)
            size = np.where(known[i] == own, begin[i + 1] - begin[i], 0)
            at = spans(begin[i], size)
            sizes.append(size)
            when.append(t[at])
            far.append(v[at])
        none = [np.zeros(0, np.int64)]
        return ids, np.concatenate(sizes or none), np.concatenate(when or none), np.concatenate(far or none)


def _grown(x: np.ndarray, n: int) -> np.ndarray:
    """``x``, or a longer copy with zeros at its end that has room for ``n``."""
    return x if n <= len(x) else np.concatenate((x, np.zeros(max(n, 2 * len(x)) - len(x), x.dtype)))


class Patch:
    """The part of a stored graph that one root's states reach, with vertices numbered as they are met."""

    def __init__(self, stored: Stored):
        self.stored, self.at, self.ids, self.m = stored, {}, [], 0
        self.start, self.size, self.low = (np.zeros(64, np.int64) for _ in range(3))
        self.when, self.far = np.zeros(1024, np.int64), np.zeros(1024, np.int64)
        self.lists: dict[int, np.ndarray] = {}

    def number(self, vertices: np.ndarray) -> np.ndarray:
        new = np.unique(np.array([v for v in vertices.tolist() if v not in self.at], np.int64))
        if len(new):
            ids, size, when, far = self.stored.read(new)
            lo, hi = len(self.ids), len(self.ids) + len(ids)
            self.start, self.size, self.low = (_grown(x, hi) for x in (self.start, self.size, self.low))
            self.when, self.far = _grown(self.when, self.m + len(when)), _grown(self.far, self.m + len(far))
            self.when[self.m : self.m + len(when)], self.far[self.m : self.m + len(far)] = when, far
            self.start[lo:hi], self.size[lo:hi] = self.m + np.cumsum(size) - size, size
            self.m += len(when)
            self.at.update(zip(ids.tolist(), range(lo, hi)))
            self.ids.extend(ids.tolist())
            self.low[lo:hi] = self.degree(np.arange(lo, hi), BEGIN)
        return np.array([self.at[v] for v in vertices.tolist()], np.int64)

    def degree(self, i: np.ndarray, now: int) -> np.ndarray:
        """Arcs that each vertex has at a time."""
        lo = self.start[i]
        hi = lo + self.size[i]
        while (open_ := lo < hi).any():
            mid = (lo + hi) >> 1
            there = open_ & (self.when[np.minimum(mid, self.m - 1)] <= now)
            lo = np.where(there, mid + 1, lo)
            hi = np.where(open_ & ~there, mid, hi)
        return lo - self.start[i]

    def degree_of(self, i: int, now: int) -> int:
        """degree() of one vertex."""
        return int(self.times(i).searchsorted(now, "right"))

    def times(self, i: int) -> np.ndarray:
        return self.when[self.start[i] : self.start[i] + self.size[i]]

    def heads(self, i: int) -> np.ndarray:
        """Numbers of the heads of all arcs that a vertex ever has."""
        if i not in self.lists:
            self.lists[i] = self.number(self.far[self.start[i] : self.start[i] + self.size[i]])
        return self.lists[i]


class State:
    """Push state of one root, as kernel.Local keeps it; reverse states are of undirected graphs."""

    def __init__(self, patch: Patch, root: int, alpha: float, rmax: float, kind: str, order: str = "sync", signs=(1, -1), now: int = BEGIN):
        self.patch, self.alpha, self.rmax, self.kind = patch, alpha, rmax, kind
        self.est, self.res, self.held = np.zeros(64), np.zeros(64), np.zeros(64, np.int64)
        self.kept = np.zeros(64, bool)  # vertices whose updates are followed: with an estimate, and the root of a reverse state
        self.queue: list[tuple[int, int, int]] = []  # (time, vertex, place in its list): their next arcs
        self.follows: dict[int, list[int]] = {}
        self.sink = self.repair_abs = 0.0
        self.updates = self.pushes = self.cost = 0
        self.now, self.order, self.signs = now, "sync", (1,)
        self.root = int(patch.number(np.array([root], np.int64))[0])
        self.fit()
        self.res[self.root] = 1.0
        if kind == "reverse":
            self.follow(self.root)
        self.drain(np.array([self.root]))
        self.order, self.signs = order, signs

    def fit(self) -> None:
        n = len(self.patch.ids)
        self.est, self.res, self.held, self.kept = (_grown(x, n) for x in (self.est, self.res, self.held, self.kept))

    def follow(self, i: int) -> None:
        if self.kept[i]:
            return
        times = self.patch.times(i)
        k = int(np.searchsorted(times, self.now, "right"))
        self.kept[i], self.held[i] = True, k
        self.follows[i] = times.tolist()
        if k < len(times):
            heapq.heappush(self.queue, (self.follows[i][k], i, k))

    def refresh(self, i: np.ndarray, now: int) -> np.ndarray:
        """Degrees at a time; residuals of reverse states that arcs passed by since are brought there, and counted."""
        d = self.patch.degree(i, now)
        s = np.flatnonzero(~self.kept[i] & (self.res[i] != 0) & (self.held[i] < d))
        if len(s):
            was, at = self.res[i[s]], i[s]
            self.res[at] = was * self.held[at] / d[s]
            self.updates += int((d[s] - self.held[at]).sum())
            self.repair_abs += float(np.abs(was - self.res[at]).sum())
        self.held[i] = d
        return d

    def refresh_one(self, i: int, now: int) -> None:
        """refresh() of one vertex that is not followed."""
        d, was, held = self.patch.degree_of(i, now), float(self.res[i]), int(self.held[i])
        if was != 0 and held < d:
            self.res[i] = new = was * held / d
            self.updates += d - held
            self.repair_abs += abs(was - new)
        self.held[i] = d

    def over(self, i: np.ndarray, sign: int) -> np.ndarray:
        r = self.res[i] * sign
        if self.kind == "reverse":
            return i[r > self.rmax]
        i = i[r > self.rmax * np.maximum(self.patch.low[i], 1)]  # degrees only grow
        return i[self.res[i] * sign > self.rmax * np.maximum(self.patch.degree(i, self.now), 1)] if len(i) else i

    def push(self, i: int, r: float) -> np.ndarray:
        """Push ``r`` of a vertex's residual; the vertices reached."""
        every = self.patch.heads(i)
        self.fit()
        self.follow(i)
        near = every[: self.held[i]]
        self.est[i] += self.alpha * r
        self.res[i] -= r
        if self.kind == "reverse":
            np.add.at(self.res, near, (1 - self.alpha) * r / self.refresh(near, self.now))
        elif len(near):
            np.add.at(self.res, near, (1 - self.alpha) * r / len(near))
        else:
            self.sink += (1 - self.alpha) * r
        self.updates += len(near)
        self.pushes += 1
        self.cost += len(near)
        return near

    def drain(self, touched: np.ndarray) -> None:
        seeds, ids = [touched], self.patch.ids  # ties go by id
        for sign in self.signs:
            start = np.unique(self.over(np.concatenate(seeds), sign))
            if self.order == "max_first":
                line = [(-self.res[u] * sign, ids[u], u) for u in start.tolist()]
                heapq.heapify(line)
                while line:
                    *_, u = heapq.heappop(line)
                    if len(self.over(np.array([u]), sign)):
                        seeds.append(self.push(u, self.res[u]))
                        for v in self.over(seeds[-1], sign).tolist():
                            heapq.heappush(line, (-self.res[v] * sign, ids[v], v))
            elif self.order == "fifo":
                line = deque(sorted(start.tolist(), key=ids.__getitem__))
                while line:
                    u = line.popleft()
                    if len(self.over(np.array([u]), sign)):
                        seeds.append(self.push(u, self.res[u]))
                        line.extend(self.over(seeds[-1], sign).tolist())
            else:
                while len(start):
                    wave = [self.push(u, r) for u, r in zip(start.tolist(), self.res[start].tolist())]
                    seeds += wave
                    start = np.unique(self.over(np.concatenate(wave), sign))

    def quiet(self, touched: list[int]) -> bool:
        """Whether surely none of a few vertices is over its limit."""
        for x in touched:
            r = abs(self.res[x])
            if r > self.rmax and (self.kind == "reverse" or r > self.rmax * (self.held[x] if self.kept[x] else self.patch.low[x])):
                return False
        return len(touched) <= 4

    def add(self, i: int, x: float) -> None:
        self.res[i] += x
        self.repair_abs += abs(x)
        self.updates += 1

    def arc(self, u: int, v: int, how: str) -> list[int]:
        """A new arc u -> v of a followed vertex, repaired lazily or eagerly; which vertices were touched."""
        a, e, d = self.alpha, float(self.est[u]), int(self.held[u])
        self.held[u] = d + 1
        if e == 0.0:
            return []
        if d == 0:
            self.sink -= (1 - a) / a * e
            self.add(v, (1 - a) / a * e)
        elif how == "lazy":
            rho = e / d
            self.est[u] = rho * (d + 1)
            self.add(u, -rho / a)
            self.add(v, (1 - a) / a * rho)
        else:
            old, moved = self.patch.heads(u)[:d], (1 - a) / a * e * (1 / (d + 1) - 1 / d)
            np.add.at(self.res, old, moved)
            self.repair_abs += abs(moved) * d
            self.updates += d
            self.add(v, (1 - a) / a * e / (d + 1))
            return [u, v, *old.tolist()]
        return [u, v]

    def arc_reverse(self, u: int, v: int, now: int) -> list[int]:
        a = self.alpha
        if not self.kept[u]:
            self.refresh_one(u, now - 1)
        e, r, head, d = float(self.est[u]), float(self.res[u]), float(self.est[v]), int(self.held[u])
        self.held[u] = d + 1
        unit = 1.0 if u == self.root else 0.0
        if not (e or r or head or unit):
            return []
        x = e + a * r - a * unit if d else 0.0
        x = (x * d + (1 - a) * head) / (d + 1)
        self.add(u, (x - e + a * unit) / a - r)
        return [u]

    def next_update(self) -> list[tuple[int, int, int]]:
        """(time, vertex, head) of the next update's arcs of followed vertices."""
        out: list[tuple[int, int, int]] = []
        while self.queue and (not out or self.queue[0][0] >> 1 == out[0][0] >> 1):
            t, u, k = self.queue[0]
            out.append((t, u, int(self.patch.heads(u)[k])))
            times = self.follows[u]
            if k + 1 < len(times):
                heapq.heapreplace(self.queue, (times[k + 1], u, k + 1))
            else:
                heapq.heappop(self.queue)
        self.fit()
        return out

    def run(self, how: str, check: bool = False) -> int:
        """All updates that are left; how many broke their cost bound, if that is checked."""
        broken = 0
        while arcs := self.next_update():
            last = arcs[0][0] >> 1
            before, added, cost = (float(np.abs(self.res).sum()), self.repair_abs, self.cost) if check else (0.0, 0.0, 0)
            if how == "reverse":
                t, u, v = arcs[0]
                first, second = (u, v) if t & 1 == 0 else (v, u), (v, u) if t & 1 == 0 else (u, v)
                touched = self.arc_reverse(*first, 2 * last)
                if u != v:
                    touched += self.arc_reverse(*second, 2 * last + 1)
            else:
                touched = [x for _, u, v in arcs for x in self.arc(u, v, how)]
            self.now = 2 * last + 1
            if not self.quiet(touched[:5]):
                self.drain(np.array(touched))
            if check:
                bound = measures.forward_update_bound(before, float(np.abs(self.res).sum()), self.repair_abs - added, self.alpha, self.rmax)
                broken += self.cost - cost > bound * (1 + 1e-9) + 1e-6
        return broken

    def named(self, x: np.ndarray) -> dict[int, float]:
        at = np.flatnonzero(x)
        return dict(zip((self.patch.ids[i] for i in at.tolist()), x[at].tolist()))


def maintain(patch: Patch, root: int, m: dict, alpha: float, seqs: list[int], end: int):
    """(counters, est, res, sink) of one root and method as the kernel gives them. ``seqs``: updates that a rebuild follows."""
    how = m["how"]
    kind = "reverse" if how.endswith("reverse") else "forward"
    k = State(patch, root, alpha, m["rmax"], kind, m.get("order", "sync"), m.get("signs", (1, -1)))
    counts, broken, t = [k.updates, k.pushes, k.cost], 0, time.perf_counter()
    if how.startswith("rebuild"):
        counts = [0, 0, 0]
        for s in seqs[: m.get("first", len(seqs))]:
            k = State(patch, root, alpha, m["rmax"], kind, now=2 * s + 1)
            counts = [x - y for x, y in zip(counts, (k.updates, k.pushes, k.cost))]
        k.updates = k.pushes = k.cost = 0
    else:
        k.repair_abs = 0.0
        broken = k.run(how, m.get("check", False))
        if kind == "reverse":
            k.refresh(np.arange(len(patch.ids)), end)
    est, res = k.named(k.est), k.named(k.res)
    row = {"residual_updates": k.updates - counts[0], "push_iterations": k.pushes - counts[1], "push_cost": k.cost - counts[2]}
    return row | {"repair_abs": k.repair_abs, "rerouted": 0, "broken": broken, "entries": len(est) + len(res), "seconds": time.perf_counter() - t}, est, res, k.sink


def fits(initial: DataFrame, events: DataFrame, methods: list[dict], alpha: float, undirected: bool, batch: int) -> bool:
    """Whether states are kept here: insertions one by one, each with a number, and thresholds by which no state can spread over the whole graph.

    A forward push from scratch costs 1 / (alpha rmax) arcs at most, a reverse one as many vertices' mean degrees.
    """
    if "seq" not in events.columns or batch != 1 or any(m["how"] not in HOWS or m.get("marks") for m in methods):
        return False
    if not undirected and any(m["how"].endswith("reverse") for m in methods):
        return False
    first = initial.agg(F.count("*").alias("m"), (F.approx_count_distinct("src") + F.approx_count_distinct("dst")).alias("n")).first()
    arcs = first["m"] * (2 if undirected else 1)
    if any(1 / (alpha * m["rmax"]) >= (first["n"] if m["how"].endswith("reverse") else arcs) for m in methods):
        return False
    got = events.agg(F.count("*").alias("all"), F.count_if((F.col("op") == 1) & (F.col("seq") >= 0)).alias("new")).first()
    return got["all"] == got["new"] and events.select("seq").distinct().count() == got["all"]
