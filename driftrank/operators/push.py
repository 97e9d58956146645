"""Forward and reverse push for many roots at once, as synchronous DataFrame rounds.

A round joins the state with adjacency lists once, explodes kept rows and the shares of active ones together and sums
them by (root, node): one reference to the state, so lineage stays linear. Lists of hubs are cut into chunks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftrank.engine import BROADCAST_ROWS, cut_lineage
from driftrank.schemas import SINK

CHUNK = 4096


def lists(arcs: DataFrame, kind: str) -> DataFrame:
    """(node, chunk, thr, nbrs): whom a push reaches and by what weight. Forward: out-neighbours, 1 / own degree;
    reverse: in-neighbours, 1 / their out-degree. thr scales the stop rule."""
    out = arcs.groupBy("src").agg(F.count("*").alias("d"))
    a = arcs.join(out, "src")
    node, far = ("src", "dst") if kind == "forward" else ("dst", "src")
    a = a.select(F.col(node).alias("node"), F.struct(F.col(far).alias("node"), (1.0 / F.col("d")).alias("w")).alias("x"), F.col("d"))
    salt = F.pmod(F.xxhash64("x.node"), F.ceil(F.col("n") / CHUNK)).cast("int")
    a = a.join(a.groupBy("node").agg(F.count("*").alias("n")), "node").withColumn("salt", salt)
    got = a.groupBy("node", "salt").agg(F.first("d").alias("d"), F.collect_list("x").alias("nbrs"))
    thr = F.col("d").cast("double") if kind == "forward" else F.lit(1.0)
    # a salt without members has no row, so the least salt of a node is where its own row is kept
    first = got.groupBy("node").agg(F.min("salt").alias("s0"))
    return got.join(first, "node").select("node", (F.col("salt") - F.col("s0")).alias("chunk"), thr.alias("thr"), "nbrs")


def start_state(roots: DataFrame) -> DataFrame:
    return roots.select(F.col("root").cast("long"), F.col("root").cast("long").alias("node"), F.lit(0.0).alias("est"), F.lit(1.0).alias("res"))


def active(sign: int, rmax: float) -> Column:
    """Over the threshold in the given direction; the sink row never is."""
    return (F.col("res") * sign > rmax * F.coalesce("thr", F.lit(1.0))) & (F.col("node") != SINK)


def one_round(adj: DataFrame, state: DataFrame, alpha: float, rmax: float, sign: int, kind: str, dangling: str = "sink") -> DataFrame:
    # lists join active rows only, so a round moves the lists of its frontier and not those of the whole state
    thr = adj.where("chunk = 0").select("node", "thr")
    known = state.join(thr, "node", "left").withColumn("on", active(sign, rmax))
    near = adj.select(F.col("node").alias("at"), "chunk", "nbrs")
    j = known.join(near, (F.col("node") == F.col("at")) & F.col("on"), "left")
    zero = F.lit(0.0)
    keep = F.array(F.struct(F.col("node"), (F.col("est") + F.when(F.col("on"), F.col("res") * alpha).otherwise(zero)).alias("est"), F.when(F.col("on"), zero).otherwise(F.col("res")).alias("res")))
    none = F.array().cast("array<struct<node:bigint,est:double,res:double>>")
    give = F.transform("nbrs", lambda x: F.struct(x["node"].alias("node"), zero.alias("est"), (x["w"] * F.col("res") * (1 - alpha)).alias("res")))
    if kind == "forward" and dangling == "root":  # as if each vertex without heads had an arc to the root
        stuck = F.array(F.struct(F.col("root").alias("node"), zero.alias("est"), (F.col("res") * (1 - alpha)).alias("res")))
    elif kind == "forward":  # mass that cannot leave collects in the sink; reverse: nobody reaches a vertex without in-edges
        stuck = F.array(F.struct(F.lit(SINK).cast("long").alias("node"), (F.col("res") * (1 - alpha)).alias("est"), zero.alias("res")))
    else:
        stuck = none
    parts = F.concat(F.when(F.coalesce("chunk", F.lit(0)) == 0, keep).otherwise(none), F.when(~F.col("on"), none).when(F.col("nbrs").isNull(), stuck).otherwise(give))
    out = j.select("root", F.explode(parts).alias("p")).select("root", "p.*")
    return out.groupBy("root", "node").agg(F.sum("est").alias("est"), F.sum("res").alias("res"))


def push(arcs: DataFrame, state: DataFrame, alpha: float = 0.2, rmax: float = 1e-4, kind: str = "forward", signs=(1, -1), cut: int = 4, max_rounds: int = 400, dangling: str = "sink") -> DataFrame:
    """Drain positive residuals until none is over the threshold, then negative ones. State in, state out.

    Raises if a sign takes over ``max_rounds`` rounds: a state that is handed out obeys its threshold. ``dangling``: where
    forward mass goes that cannot leave a vertex: to the sink, back to the root ("root"), or nowhere ("error" raises).
    """
    if dangling == "error" and not arcs.select(F.col("dst").alias("src")).join(arcs, "src", "left_anti").isEmpty():
        raise ValueError("a vertex has no out-edge")
    adj = cut_lineage(lists(arcs, kind), "adjacency")
    thr = adj.where("chunk = 0").select("node", "thr")
    state = state.select("root", "node", "est", "res")
    for sign in signs:
        done = 0
        while not state.join(thr, "node", "left").where(active(sign, rmax)).isEmpty():
            if done >= max_rounds:
                raise RuntimeError(f"residuals over {rmax} are left after {done} rounds")
            for _ in range(cut):
                state = one_round(adj, state, alpha, rmax, sign, kind, dangling)
            done += cut
            state = cut_lineage(state)
    return state


def counted(arcs: DataFrame, state: DataFrame, alpha: float = 0.2, rmax: float = 1e-4, kind: str = "forward", max_rounds: int = 400) -> tuple[DataFrame, DataFrame]:
    """Positive rounds one by one: (state, (root, pushes, cost)); the cost of a push is the number of neighbours it reaches."""
    adj = cut_lineage(lists(arcs, kind), "adjacency")
    reach = cut_lineage(adj.groupBy("node").agg(F.min("thr").alias("thr"), F.sum(F.size("nbrs")).alias("reach")), "reach")
    seen = []
    for _ in range(max_rounds):
        on = state.join(reach, "node", "left").where(active(1, rmax))
        step = cut_lineage(on.groupBy("root").agg(F.count("*").alias("pushes"), F.sum(F.coalesce("reach", F.lit(0))).alias("cost")), "cost")
        if step.isEmpty():
            break
        seen.append(step)
        state = cut_lineage(one_round(adj, state, alpha, rmax, 1, kind))
    else:
        raise RuntimeError(f"residuals over {rmax} are left after {max_rounds} rounds")
    every = step
    for s in seen:
        every = every.union(s)
    return state, every.groupBy("root").agg(F.sum("pushes").alias("pushes"), F.sum("cost").cast("long").alias("cost"))


def forward(arcs, state, alpha=0.2, rmax=1e-4, **kw) -> DataFrame:
    return push(arcs, state, alpha, rmax, "forward", **kw)


def reverse(arcs, state, alpha=0.2, rmax=1e-4, **kw) -> DataFrame:
    return push(arcs, state, alpha, rmax, "reverse", **kw)


def spread(arcs: DataFrame, state: DataFrame, alpha: float = 0.2, rounds: int = 60, kind: str = "forward") -> DataFrame:
    """State after all residual mass was pushed ``rounds`` times; (1 - alpha) ** rounds of it is left at most."""
    adj = cut_lineage(lists(arcs, kind), "adjacency")
    for k in range(rounds):
        state = one_round(adj, state, alpha, 0.0, 1, kind)
        if k % 4 == 3:
            state = cut_lineage(state)
    return state


WHOLE = 4_000_000  # arcs up to which rounds take the graph as it is
SLICED = 8_000_000  # arcs over which rounds are array operations over a stored graph


def within(arcs: DataFrame, roots: DataFrame) -> DataFrame:
    """Those arcs that forward mass from the roots can ever use: rounds from them end the same, and join no other lists.

    The vertices met are found wave by wave. Once the next wave may be more than is broadcast, all arcs are returned.
    """
    met = wave = cut_lineage(roots.select(F.col("root").cast("long").alias("node")).distinct(), "met")
    seen = wave.count()
    while not wave.isEmpty():
        if seen > BROADCAST_ROWS:
            return arcs
        to = arcs.join(F.broadcast(wave), F.col("src") == F.col("node"), "left_semi").select(F.col("dst").alias("node")).distinct()
        wave = cut_lineage(to.join(F.broadcast(met), "node", "left_anti"), "met")
        met, seen = met.union(wave), seen + wave.count()
    return cut_lineage(arcs.join(F.broadcast(met), F.col("src") == F.col("node"), "left_semi"), "arcs")


def power_iteration(arcs: DataFrame, roots: DataFrame, alpha: float = 0.2, rounds: int = 60, kind: str = "forward") -> DataFrame:
    """(root, node, ppr) by ``rounds`` full pushes from every root."""
    size = arcs.count()
    if size > SLICED:
        from driftrank.operators import slices

        return slices.Sliced(arcs, roots, kind).run(alpha, rounds)
    if kind == "forward" and size > WHOLE:  # a reverse push weighs by degrees, which need all arcs
        arcs = within(arcs, roots)
    state = spread(arcs, start_state(roots), alpha, rounds, kind)
    return state.where(F.col("node") != SINK).select("root", "node", F.col("est").alias("ppr"))


def potential(arcs: DataFrame, alpha: float = 0.2, rounds: int = 24) -> DataFrame:
    """(node, phi): scores from all vertices at once, each weighted by its in-degree; the sink row is part of it.

    Mass not yet settled after ``rounds`` counts where it is: on undirected graphs that is already exact.
    """
    start = arcs.groupBy(F.col("dst").alias("node")).agg(F.count("*").cast("double").alias("res"))
    state = spread(arcs, start.select(F.lit(0).cast("long").alias("root"), "node", F.lit(0.0).alias("est"), "res"), alpha, rounds)
    return state.select("node", (F.col("est") + F.col("res")).alias("phi"))


def top_k(scores: DataFrame, k: int, score: str = "est") -> DataFrame:
    """(root, rank, node, score); ties by node id."""
    from pyspark.sql.window import Window

    w = Window.partitionBy("root").orderBy(F.col(score).desc(), "node")
    return scores.where(F.col("node") != SINK).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("root", "rank", "node", F.col(score).alias("score"))
