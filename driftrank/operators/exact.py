"""Exact scores by a linear solve, for graphs of a checked number of vertices."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dense_solve(arcs: DataFrame, roots: DataFrame, alpha: float = 0.2, limit: int = 2000) -> DataFrame:
    """(root, node, ppr) of distinct ``arcs``, for roots that have an arc; raises over ``limit`` vertices.

    Mass that reaches a vertex without heads is lost there, as with the sink.
    """
    ids = arcs.select(F.col("src").alias("node")).union(arcs.select("dst")).distinct()
    if ids.count() > limit:
        raise ValueError(f"over {limit} vertices: use push.power_iteration")
    table = np.sort(ids.toPandas()["node"].to_numpy())
    at = arcs.toPandas()  # limit ** 2 rows at most
    step = np.zeros((len(table), len(table)))
    step[np.searchsorted(table, at["src"]), np.searchsorted(table, at["dst"])] = 1.0
    step /= np.maximum(step.sum(axis=1, keepdims=True), 1.0)
    who = np.intersect1d(roots.toPandas()["root"].to_numpy(dtype=np.int64), table)
    unit = (table[None] == who[:, None]).astype(float)
    ppr = np.linalg.solve(np.eye(len(table)) - (1 - alpha) * step.T, alpha * unit.T).T
    r, c = np.nonzero(ppr > 0)
    return arcs.sparkSession.createDataFrame(pd.DataFrame({"root": who[r], "node": table[c], "ppr": ppr[r, c]}), "root long, node long, ppr double")
