"""Repairs of push states after edge updates, and the local identities that they keep.

A batch is a DataFrame (src, dst, op) of arcs, op +1 or -1, that holds each arc once. Lazy repair keeps a vertex's
share per out-edge and touches no other neighbour; eager repair rewrites the share at every neighbour; reverse repair
solves the changed vertex's own identity. A batch is broadcast behind a count. Vertices without old or new out-edges follow the sink rule.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.engine import side_hint
from driftrank.schemas import SINK


def _change(batch: DataFrame, old: DataFrame) -> DataFrame:
    """(u, d_old, d_new) of all sources in the batch; ``old`` has (node, d_out)."""
    c = batch.groupBy(F.col("src").alias("u")).agg(F.sum("op").alias("k"))
    c = c.join(old.select(F.col("node").alias("u"), "d_out"), "u", "left")
    return c.select("u", F.coalesce("d_out", F.lit(0)).cast("double").alias("d_old"), (F.coalesce("d_out", F.lit(0)) + F.col("k")).cast("double").alias("d_new"))


def _merged(state: DataFrame, *deltas: DataFrame) -> DataFrame:
    out = state.select("root", "node", "est", "res")
    for d in deltas:
        out = out.union(d.select("root", "node", "est", "res"))
    return out.groupBy("root", "node").agg(F.sum("est").alias("est"), F.sum("res").alias("res"))


def lazy_forward(state: DataFrame, batch: DataFrame, d_old: DataFrame, alpha: float = 0.2) -> DataFrame:
    """O(1) a root and update: only u and the heads of changed arcs get new values; no scan of the graph's edges."""
    at_u = state.where(F.col("node") != SINK).join(side_hint(batch)(_change(batch, d_old)), F.col("node") == F.col("u"))
    normal = (F.col("d_old") > 0) & (F.col("d_new") > 0)
    rho = F.col("est") / F.col("d_old")
    moved = F.col("d_new") - F.col("d_old")
    own = at_u.where(normal).select("root", "node", (rho * moved).alias("est"), (-rho * moved / alpha).alias("res"))
    share = F.when(F.col("d_old") > 0, rho).otherwise(F.col("est") / F.col("d_new"))
    heads = at_u.join(side_hint(batch)(batch), F.col("u") == F.col("src"))
    heads = heads.select("root", F.col("dst").alias("node"), F.lit(0.0).alias("est"), (share * F.col("op") * (1 - alpha) / alpha).alias("res"))
    return _merged(state, own, heads, _sink_change(at_u, alpha))


def _sink_change(at_u: DataFrame, alpha: float) -> DataFrame:
    """First out-edge: the sink gives back what the vertex had sent there; last one removed: it takes it."""
    sent = F.col("est") * (1 - alpha) / alpha
    way = F.when(F.col("d_old") == 0, -sent).when(F.col("d_new") == 0, sent)
    return at_u.where("d_old = 0 or d_new = 0").select("root", F.lit(SINK).cast("long").alias("node"), way.alias("est"), F.lit(0.0).alias("res"))


def eager_forward(state: DataFrame, batch: DataFrame, arcs_old: DataFrame, d_old: DataFrame, alpha: float = 0.2) -> DataFrame:
    """The baseline: the share at every old and new out-neighbour is rewritten; reads all arcs of changed vertices."""
    at_u = state.where(F.col("node") != SINK).join(side_hint(batch)(_change(batch, d_old)), F.col("node") == F.col("u"))
    near = arcs_old.join(batch.select("src").distinct(), "src").select("src", "dst", F.lit(1).alias("was"), F.lit(0).alias("op"))
    both = near.union(batch.select("src", "dst", F.lit(0), "op")).groupBy("src", "dst").agg(F.sum("was").alias("was"), F.sum("op").alias("op"))
    before = F.when(F.col("was") > 0, 1 / F.col("d_old")).otherwise(0.0)
    after = F.when(F.col("was") + F.col("op") > 0, 1 / F.col("d_new")).otherwise(0.0)
    delta = at_u.join(both, F.col("u") == F.col("src")).select("root", F.col("dst").alias("node"), F.lit(0.0).alias("est"), (F.col("est") * (1 - alpha) / alpha * (after - before)).alias("res"))
    return _merged(state, delta, _sink_change(at_u, alpha))


def reverse(state: DataFrame, batch: DataFrame, d_old: DataFrame, alpha: float = 0.2) -> DataFrame:
    """O(1) a root and update: residual of u from u's own row and the heads' estimates. Estimates stay."""
    change = _change(batch, d_old)
    est_v = batch.join(state.select(F.col("node").alias("dst"), "root", "est"), "dst").groupBy("root", F.col("src").alias("u")).agg(F.sum(F.col("op") * F.col("est")).alias("heads"))
    roots = state.select("root").distinct()
    # rows concerned: u has a row, a head has one, or u is the root itself
    rows = state.join(change.select(F.col("u").alias("node")), "node").select("root", F.col("node").alias("u"), "est", "res", F.lit(0.0).alias("heads"))
    rows = rows.union(est_v.select("root", "u", F.lit(0.0), F.lit(0.0), "heads")).union(roots.join(change.select("u"), F.col("root") == F.col("u")).select("root", "u", F.lit(0.0), F.lit(0.0), F.lit(0.0)))
    rows = rows.groupBy("root", "u").agg(F.sum("est").alias("est"), F.sum("res").alias("res"), F.sum("heads").alias("heads")).join(change, "u")
    unit = F.when(F.col("u") == F.col("root"), 1.0).otherwise(0.0)
    x_old = F.when(F.col("d_old") > 0, F.col("est") + alpha * F.col("res") - alpha * unit).otherwise(0.0)
    x_new = F.when(F.col("d_new") > 0, (x_old * F.col("d_old") + (1 - alpha) * F.col("heads")) / F.col("d_new")).otherwise(0.0)
    new = (x_new - F.col("est") + alpha * unit) / alpha
    return _merged(state, rows.select("root", F.col("u").alias("node"), F.lit(0.0).alias("est"), (new - F.col("res")).alias("res")))


def forward_defect(arcs: DataFrame, state: DataFrame, alpha: float = 0.2) -> DataFrame:
    """(root, node, defect): est + alpha res - alpha [node = root] - (1 - alpha) sum of in-neighbours' est / degree; 0 if valid."""
    d = arcs.groupBy("src").agg(F.count("*").alias("d"))
    s = state.where(F.col("node") != SINK)
    sent = s.join(arcs.join(d, "src"), F.col("node") == F.col("src")).select("root", F.col("dst").alias("node"), (-(1 - alpha) * F.col("est") / F.col("d")).alias("x"))
    own = s.select("root", "node", (F.col("est") + alpha * F.col("res") - F.when(F.col("node") == F.col("root"), alpha).otherwise(0.0)).alias("x"))
    return own.union(sent).groupBy("root", "node").agg(F.sum("x").alias("defect"))


def reverse_defect(arcs: DataFrame, state: DataFrame, alpha: float = 0.2) -> DataFrame:
    d = arcs.groupBy("src").agg(F.count("*").alias("d"))
    got = state.join(arcs.join(d, "src"), F.col("node") == F.col("dst")).select("root", F.col("src").alias("node"), (-(1 - alpha) * F.col("est") / F.col("d")).alias("x"))
    own = state.select("root", "node", (F.col("est") + alpha * F.col("res") - F.when(F.col("node") == F.col("root"), alpha).otherwise(0.0)).alias("x"))
    return own.union(got).groupBy("root", "node").agg(F.sum("x").alias("defect"))
