"""Rounds that push all residual mass, as array operations over a stored graph.

Vertices are dealt to slices, and arcs to the slice of the vertex that mass arrives at. A round is one job: the task of a slice
reads what all vertices give away, root by root, and sums it over its own arcs. A task holds the arcs of one slice and one
number a vertex; arcs, numbers and states lie in the shared folder.
"""

from __future__ import annotations

import os
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank import engine
from driftrank.operators.patches import _place

PART = 4_000_000  # arcs of a slice, about


def _put(folder: str, name: str, *arrays: np.ndarray) -> None:
    """A file of arrays of numbers of 8 bytes."""
    fs, at = _place(folder)
    fs.create_dir(os.path.dirname(f"{at}/{name}"), recursive=True)
    tmp = f"{at}/{name}-{TaskContext.get().taskAttemptId()}"
    with fs.open_output_stream(tmp) as out:
        out.write(np.array([len(arrays), *(x.size for x in arrays)], np.int64).tobytes())
        for x in arrays:
            out.write(np.ascontiguousarray(x).tobytes())
    fs.move(tmp, f"{at}/{name}")


def _get(folder: str, name: str) -> list[np.ndarray]:
    """The arrays of a file, as whole numbers; a local one is mapped."""
    fs, at = _place(folder)
    if isinstance(fs, pafs.LocalFileSystem):
        raw = np.memmap(f"{at}/{name}", np.int64, "r")
    else:
        with fs.open_input_file(f"{at}/{name}") as f:
            raw = np.frombuffer(f.read(), np.int64)
    k = int(raw[0])
    return np.split(raw[k + 1 :], np.cumsum(raw[1:k]))


def _columns(batches) -> list[np.ndarray]:
    """All columns but the first of all batches; none if there are no rows."""
    got = [[x.to_numpy(zero_copy_only=False) for x in b.columns[1:]] for b in batches if b.num_rows]
    return [np.concatenate(c) for c in zip(*got, strict=True)]


def keep(rows: DataFrame, folder: str, name: str) -> list[str]:
    """Names of files that hold ``rows`` of whole numbers in their order, a file a partition."""

    def write(batches):
        got = [[x.to_numpy(zero_copy_only=False) for x in b.columns] for b in batches if b.num_rows]
        if got:
            k = TaskContext.get().partitionId()
            _put(folder, f"{name}-{k}", *(np.concatenate(c) for c in zip(*got, strict=True)))
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64())], ["k"])

    rows = rows.select(*(F.col(c).cast("long") for c in rows.columns))
    return [f"{name}-{k}" for k in sorted(r["k"] for r in rows.mapInArrow(write, "k long").collect())]


def kept(folder: str, names: list[str], columns: int) -> list[np.ndarray]:
    """The columns of rows from keep()."""
    parts = [_get(folder, n) for n in names] or [[np.zeros(0, np.int64)] * columns]
    return [np.concatenate(c) for c in zip(*parts, strict=True)]


class Sliced:
    """A stored graph in ``count`` slices, in which the mass of ``roots`` is pushed; kind 'forward' or 'reverse'."""

    def __init__(self, arcs: DataFrame, roots: DataFrame, kind: str):
        self.spark, self.kind = arcs.sparkSession, kind
        self.folder = folder = f"{engine.shared_folder(self.spark)}/slices-{uuid.uuid4().hex}"
        self.count = count = max(1, -(-arcs.count() // PART))
        self.roots = sorted(int(r["root"]) for r in roots.select("root").collect())
        slot = lambda c: F.pmod(F.shiftright(c, 3), F.lit(count)).cast("int").alias("slot")
        ends = arcs.select(F.col("src").alias("node"), F.lit(1).alias("d")).union(arcs.select("dst", F.lit(0)))
        ends = ends.union(roots.select("root", F.lit(0))).groupBy("node").agg(F.sum("d").alias("d"))

        def vertices(batches):
            if got := _columns(batches):
                order = np.argsort(got[0])
                ids, d = (x[order] for x in got)
                k = int(ids[0] >> 3) % count
                _put(folder, f"vertices-{k}", ids, d)
                yield told([k], [len(ids)])

        def told(k: list[int], n: list[int]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(k, pa.int64()), pa.array(n, pa.int64())], ["k", "n"])

        dealt = ends.select(slot("node"), F.col("node").cast("long"), F.col("d").cast("long")).repartitionById(count, F.col("slot"))
        sizes = {r["k"]: r["n"] for r in dealt.mapInArrow(vertices, "k long, n long").collect()}
        self.sizes = sizes = dict(sorted(sizes.items()))  # slices without vertices have no files
        begin = dict(zip(sizes, np.cumsum([0, *sizes.values()]).tolist()))
        n = sum(sizes.values())

        def lists(batches):
            if not (got := _columns(batches)):
                return
            own, far = got
            k = int(own[0] >> 3) % count
            at = np.searchsorted(_get(folder, f"vertices-{k}")[0], own)
            there = (far >> 3) % count
            if count <= 1 << 16:
                there = there.astype(np.uint16)  # sorted by counting
            order = np.argsort(there, kind="stable")
            cuts = np.searchsorted(there[order], np.arange(count + 1))
            key = at * n
            for j in np.flatnonzero(np.diff(cuts)).tolist():
                which = order[cuts[j] : cuts[j + 1]]
                key[which] += begin[j] + np.searchsorted(_get(folder, f"vertices-{j}")[0], far[which])
            key.sort()
            at, far = np.divmod(key, n)
            first = np.flatnonzero(np.diff(at, prepend=-1))
            _put(folder, f"arcs-{k}", at[first], first, far)
            yield told([k], [len(far)])

        to, frm = ("dst", "src") if kind == "forward" else ("src", "dst")
        dealt = arcs.select(slot(to), F.col(to).cast("long"), F.col(frm).cast("long")).repartitionById(count, F.col("slot"))
        self.reached = {r["k"] for r in dealt.mapInArrow(lists, "k long, n long").collect()}

    def tasks(self, work, schema: str) -> DataFrame:
        """``work`` (slice to arrays of the schema's columns, or None) for every slice, each in its own task."""
        names = [c.split()[0] for c in schema.split(", ")]

        def each(batches):
            for b in batches:
                for k in b.column(0).to_pylist():
                    for got in work(k) if k in sizes else ():
                        yield pa.RecordBatch.from_arrays([pa.array(x) for x in got], names)

        sizes = self.sizes
        return self.spark.range(0, self.count, 1, self.count).mapInArrow(each, schema)

    def run(self, alpha: float, rounds: int) -> DataFrame:
        """(root, node, ppr): estimates after so many rounds, of all vertices that mass has come to.

        A state's file holds what each vertex gives away (root by root), and its estimate after the next round.
        """
        folder, sizes, roots, reached, kind = self.folder, self.sizes, self.roots, self.reached, self.kind

        def come(k: int, t: int, d: np.ndarray):
            """Residuals of a slice after ``t`` rounds, root by root."""
            if t and k in reached:
                at, first, far = _get(folder, f"arcs-{k}")
                given = [_get(folder, f"state-{t - 1}/{j}")[0].view(np.float64).reshape(len(roots), -1) for j in sizes]
            for i, root in enumerate(roots):
                res = np.zeros(sizes[k])
                if t == 0:
                    res[_get(folder, f"vertices-{k}")[0] == root] = 1.0
                elif k in reached:
                    res[at] = np.add.reduceat(np.concatenate([g[i] for g in given])[far], first)
                    if kind == "reverse":
                        res *= (1 - alpha) / np.maximum(d, 1)
                yield res

        def settled(k: int, t: int) -> np.ndarray:
            """Estimates of a slice after ``t`` rounds."""
            return _get(folder, f"state-{t - 1}/{k}")[1].view(np.float64).reshape(len(roots), -1) if t else np.zeros((len(roots), sizes[k]))

        def step(t: int):
            def work(k: int):
                d = _get(folder, f"vertices-{k}")[1]
                est, give = settled(k, t) + 0.0, np.zeros((len(roots), sizes[k]))
                for i, res in enumerate(come(k, t, d)):
                    est[i] += alpha * res
                    give[i] = res if kind == "reverse" else np.where(d > 0, (1 - alpha) * res / np.maximum(d, 1), 0.0)
                _put(folder, f"state-{t}/{k}", give, est)
                yield (np.array([sizes[k]]),)

            return work

        def last(k: int):
            ids, d = _get(folder, f"vertices-{k}")
            est = settled(k, rounds)
            for i, res in enumerate(come(k, rounds, d)):
                here = (est[i] != 0) | (res != 0)
                yield np.full(int(here.sum()), roots[i]), ids[here], est[i][here]

        fs, at = _place(folder)
        for t in range(rounds if roots else 0):
            self.tasks(step(t), "n long").agg(F.sum("n")).collect()
            if t:
                fs.delete_dir(f"{at}/state-{t - 1}")
        return engine.cut_lineage(self.tasks(last, "root long, node long, ppr double"), "ppr")
