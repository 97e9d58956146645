"""The published experiments on the given tables; each returns (graph, method, metric, value)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.functions import measures
from driftrank.operators import kernel, push
from driftrank.sources import graph as G


def arrivals(spark, sf_dir: str, name: str, updates: int | None = None, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """First half of a random edge order, and the events that follow (the first ``updates`` of them)."""
    order = push.cut_lineage(G.permutation(G.build(spark, sf_dir, name), seed), "order")
    half = order.count() // 2
    last = half + (updates if updates is not None else half + 1)
    later = order.where((F.col("pos") > half) & (F.col("pos") <= last))
    return order.where(F.col("pos") <= half).select("src", "dst"), later.select(F.col("pos").alias("seq"), "src", "dst", F.lit(1).alias("op"))


def sampled(edges: DataFrame, k: int, undirected: bool = True) -> DataFrame:
    """``k`` roots, written once: they are asked for again and again."""
    return push.cut_lineage(G.sample_roots(G.ends(edges) if undirected else edges, k), "roots")


def _tidy(graph: str, wide: DataFrame, names: list[str]) -> DataFrame:
    pairs = F.array(*(F.struct(F.lit(n).alias("metric"), F.round(F.col(n).cast("double"), 6).alias("value")) for n in names))
    return wide.select(F.lit(graph).alias("graph"), "method", F.explode(pairs).alias("x")).select("graph", "method", "x.metric", "x.value")


FINER = 100  # how many times finer than the states the truth is at least


def _truth(first: DataFrame, later: DataFrame, who: DataFrame, than: float, how: str = "lazy") -> DataFrame:
    """States of the graph after all arrivals, pushed from scratch to the published benchmark's threshold, 0.02 / vertices.

    On a small graph that is coarser than the states it is to judge, so it is ``than`` / FINER at most.
    """
    end = first.union(later.select("src", "dst"))
    rmax = min(0.02 / G.stats(G.undirect(end)).first()["n"], than / FINER)
    return kernel.run(end, later.limit(0), who, [{"name": "truth", "how": how, "rmax": rmax}])[0]


def _with_ratios(tidy: DataFrame, *pairs: tuple[str, str]) -> DataFrame:
    tidy = push.cut_lineage(tidy, "report")
    out = tidy
    for of, to in pairs:
        out = out.unionByName(measures.ratios(tidy, of, to))
    return out


def table2(spark, sf_dir, graph="g_dense", roots=100, updates=None, rmax_lazy=7e-7, rmax_eager=1e-6, seconds=False) -> DataFrame:
    """Lazy against eager repair, at the published thresholds and at equal ones."""
    first, later = arrivals(spark, sf_dir, graph, updates)
    r = sampled(first, roots)
    methods = [{"name": "lazy", "how": "lazy", "rmax": rmax_lazy}, {"name": "eager", "how": "eager", "rmax": rmax_eager}, {"name": "eager_equal", "how": "eager", "rmax": rmax_lazy}]
    states, trace = kernel.run(first, later, r, methods)
    wide = measures.summary(trace).join(measures.median_l1(states, _truth(first, later, r, min(rmax_lazy, rmax_eager))), "method")
    names = ["residual_updates", "push_iterations", "push_cost", "repair_abs", "entries", "l1_error", *(["seconds"] if seconds else [])]
    return _with_ratios(_tidy(graph, wide, names), ("eager", "lazy"), ("eager_equal", "lazy"))


def table3_4(spark, sf_dir, graph="g_dense", k=50, rmax=5e-5, r=16000, roots=100, updates=None, seconds=False) -> DataFrame:
    """Top k by lazily kept push states against a rerouted walk index; the truth is pushed from scratch at the end."""
    first, later = arrivals(spark, sf_dir, graph, updates)
    who = sampled(first, roots)
    methods = [{"name": "push", "how": "lazy", "rmax": rmax}, {"name": "walks", "how": "walks", "r": r}]
    states, trace = kernel.run(first, later, who, methods)
    states = push.cut_lineage(states)
    truth = push.top_k(_truth(first, later, who, rmax), k)
    scores = [measures.accuracy(push.top_k(states.where(F.col("method") == m), k), truth, k).agg(F.percentile("accuracy", 0.5).alias("accuracy")).withColumn("method", F.lit(m)) for m in ("push", "walks")]
    wide = measures.summary(trace).join(scores[0].unionByName(scores[1]), "method")
    wide = wide.withColumn("bytes", F.when(F.col("method") == "walks", measures.walk_bytes(r, 0.2)).otherwise(F.col("entries") * 8))
    return _with_ratios(_tidy(graph, wide, ["accuracy", "bytes", *(["seconds"] if seconds else [])]), ("walks", "push"))


def figure1(spark, sf_dir, graph="g_mid", rmax=1e-4, roots=100, updates=None, first_rebuilds=1000, seconds=False, points=50) -> DataFrame:
    """Reverse repair against rebuilding from scratch after each insertion, the latter scaled from its first updates.

    The cumulative cost of the repairs is told by the line through ``points`` of its curve, their error by the median l1 distance
    from states of a finer threshold.
    """
    first, later = arrivals(spark, sf_dir, graph, updates)
    updates = later.count()
    first_rebuilds = min(first_rebuilds, updates)
    who = sampled(first, roots)
    methods = [{"name": "reverse", "how": "reverse", "rmax": rmax, "marks": points}, {"name": "rebuild", "how": "rebuild_reverse", "rmax": rmax, "first": first_rebuilds}]
    states, trace = kernel.run(first, later, who, methods)
    scale = F.when(F.col("method") == "rebuild", updates / first_rebuilds).otherwise(1.0)
    wide = measures.summary(trace).select("method", *((F.col(c) * scale).alias(c) for c in ("residual_updates", "push_iterations", "push_cost", "seconds")))
    told = _tidy(graph, wide, ["residual_updates", "push_iterations", "push_cost", *(["seconds"] if seconds else [])])
    error = measures.median_l1(states.where("method = 'reverse'"), _truth(first, later, who, rmax, "reverse"))
    own = measures.curve(trace, "seconds" if seconds else "push_cost").join(error, "method")
    return _with_ratios(told, ("rebuild", "reverse")).unionByName(_tidy(graph, own, ["slope", "intercept", "r2", "l1_error"]))


def amortization(spark, sf_dir, graph="g_dense", order="random", rmax=1e-3, roots=100) -> DataFrame:
    """Cost of keeping reverse states fresh over all arrivals after the first half, in a given order, next to one build from scratch.

    ``push_cost`` and ``repair_abs`` are means over targets; ``scratch_cost`` is the mean bound of one build, average degree / (alpha rmax).
    """
    every = G.permutation(G.build(spark, sf_dir, graph)) if graph != "g_dense" else G.arrival_by(spark, sf_dir, order)
    every = push.cut_lineage(every, "order")
    half = every.count() // 2
    first = every.where(F.col("pos") <= half).select("src", "dst")
    later = every.where(F.col("pos") > half).select(F.col("pos").alias("seq"), "src", "dst", F.lit(1).alias("op"))
    undirected = graph != "g_next"
    who = sampled(first, roots, undirected)
    _, trace = kernel.run(first, later, who, [{"name": f"reverse_{order}", "how": "reverse", "rmax": rmax}], 0.2, undirected)
    size = G.mean_degree(every, undirected)
    wide = measures.summary(trace).crossJoin(F.broadcast(size)).withColumn("scratch_cost", F.col("avg_degree") / (0.2 * rmax))  # one row
    return _tidy(graph, wide, ["residual_updates", "push_iterations", "push_cost", "repair_abs", "scratch_cost"])


def toggles(spark, sf_dir, rmax=1e-5, roots=100, updates=None) -> DataFrame:
    """Insertions and deletions: the user-key stream from an empty graph on, lazy and reverse repair."""
    ev = G.resolve_toggles(G.toggles(spark, sf_dir)).select("ts", "seq", "src", "dst", "op")
    if updates is not None:
        ev = ev.orderBy("ts", "seq").limit(updates)
    ev = push.cut_lineage(ev.select("seq", "src", "dst", "op"), "events")  # read again and again
    who = ev.select(F.col("src").alias("root")).distinct().orderBy(F.md5(F.col("root").cast("string"))).limit(roots)
    methods = [{"name": h, "how": h, "rmax": rmax} for h in ("lazy", "eager", "reverse")]
    _, trace = kernel.run(ev.select("src", "dst").limit(0), ev, who, methods)
    return _tidy("g_toggle", measures.summary(trace), ["residual_updates", "push_iterations", "push_cost", "entries"])


def sweep(spark, sf_dir, graph="g_dense", what="order", roots=100, updates=None, rmax=5e-5) -> DataFrame:
    """Ablations: push order, sign phases, thresholds."""
    first, later = arrivals(spark, sf_dir, graph, updates)
    grid = {
        "order": [{"order": o} for o in ("max_first", "fifo", "sync")],
        "rmax": [{"rmax": rmax * f} for f in (4, 1, 0.25)],
        "signs": [{"signs": (1, -1)}, {"signs": (-1, 1)}],
    }[what]
    methods = [{"name": f"{what}={next(iter(g.values()))}", "how": "lazy", "rmax": rmax} | g for g in grid]
    _, trace = kernel.run(first, later, sampled(first, roots), methods)
    return _tidy(graph, measures.summary(trace), ["residual_updates", "push_iterations", "push_cost", "entries"])
