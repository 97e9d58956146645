"""Connected components of a distributed edge list, by contractions inside partitions and alternating star contractions.

Edges never reach the driver; only the number of changed rows does. Lineage is cut by Parquet in the shared folder.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.llm.words import dropped, written

LOCAL = 1 << 20


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction: link neighbours (all larger ones, or the smaller ones and oneself) to the least neighbour."""
    if large:
        n = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select(F.col("b"), F.col("a")))
        low = n.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        out = n.where("v > u").join(low, "u").select(F.col("v").alias("x"), F.col("m").alias("y"))
    else:
        n = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v")
        low = n.groupBy("u").agg(F.min("v").alias("m"))
        out = n.join(low, "u").select(F.col("v").alias("x"), F.col("m").alias("y")).union(low.select("u", "m"))
    return out.where("x <> y").select(F.greatest("x", "y").alias("a"), F.least("x", "y").alias("b")).distinct()


def _min_labels(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node of its component) for the nodes of some edges that are not the least themselves."""
    ids, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    up = np.arange(len(ids))
    while True:
        p, q = up[x], up[y]
        apart = p != q
        if not apart.any():
            break
        np.minimum.at(up, np.maximum(p, q)[apart], np.minimum(p, q)[apart])
        while (up[up] != up).any():
            up = up[up]
    own = np.flatnonzero(up != np.arange(len(ids)))
    return ids[own], ids[up[own]]


def _contracted(edges: DataFrame) -> DataFrame:
    """Each run of up to LOCAL edges of a partition as stars around least nodes: fewer rounds, without an exchange."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def stars():
            a, b = _min_labels(*(np.concatenate(x) for x in zip(*held, strict=True)))
            return pa.record_batch({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

        for r in batches:
            held.append((r.column(0).to_numpy(), r.column(1).to_numpy()))
            n += r.num_rows
            if n >= LOCAL:
                yield stars()
                held, n = [], 0
        if n:
            yield stars()

    return edges.select("a", "b").mapInArrow(run, "a long, b long")


def _sums(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum("b"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component): for each endpoint the least id it is connected with. Isolated ids do not appear."""
    e = edges.select(F.greatest(a, b).cast("long").alias("a"), F.least(a, b).cast("long").alias("b")).where("a <> b").distinct()
    e = written(_contracted(e), "cc")
    for _ in range(max_rounds):
        # read again, small files share a task, so a contraction sees more than the one before
        last, e = e, written(_contracted(e), "cc")
        before = _sums(e)
        older, e = e, written(_star(_star(e, True), False), "cc")
        dropped(last, older)
        if _sums(e) == before:
            break
    else:
        raise RuntimeError(f"components are not settled after {max_rounds} rounds")
    roots = e.groupBy("a").agg(F.min("b").alias("b"))
    return roots.select(F.col("a").alias("node"), F.col("b").alias("component")).union(roots.select("b", "b").distinct())
