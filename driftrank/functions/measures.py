"""Cost and accuracy measures, and checks of the published identities and bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.schemas import SINK


def errors(state: DataFrame, truth: DataFrame, degrees: DataFrame) -> DataFrame:
    """(root, l1, max_abs, max_by_degree) of est against ppr."""
    s = state.where(F.col("node") != SINK).select("root", "node", "est")
    j = s.join(truth, ["root", "node"], "full").join(degrees.select("node", "d_out"), "node", "left")
    gap = F.abs(F.coalesce("est", F.lit(0.0)) - F.coalesce("ppr", F.lit(0.0)))
    return j.groupBy("root").agg(F.sum(gap).alias("l1"), F.max(gap).alias("max_abs"), F.max(gap / F.greatest(F.coalesce("d_out", F.lit(1)), F.lit(1))).alias("max_by_degree"))


def certificate(state: DataFrame, degrees: DataFrame, kind: str) -> DataFrame:
    """(root, bound): the greatest residual, per degree for forward states; the stop rule keeps it under rmax."""
    j = state.where(F.col("node") != SINK).join(degrees.select("node", "d_out"), "node", "left")
    scale = F.greatest(F.coalesce("d_out", F.lit(1)), F.lit(1)) if kind == "forward" else F.lit(1)
    return j.groupBy("root").agg(F.max(F.abs("res") / scale).alias("bound"))


def storage(state: DataFrame) -> DataFrame:
    """(root, entries, bytes): nonzero numbers, 8 bytes each."""
    n = F.count_if(F.col("est") != 0) + F.count_if(F.col("res") != 0)
    return state.where(F.col("node") != SINK).groupBy("root").agg(n.alias("entries"), (n * 8).alias("bytes"))


def walk_bytes(r: int, alpha: float, with_index: bool = False) -> int:
    return int(r / alpha * 4 * (2 if with_index else 1))


def accuracy(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(root, accuracy): share of the true top k that was found."""
    hit = truth.select("root", "node").join(found.select("root", "node"), ["root", "node"], "left_semi")
    return truth.select("root").distinct().join(hit.groupBy("root").count(), "root", "left").select("root", (F.coalesce("count", F.lit(0)) / k).alias("accuracy"))


def summary(trace: DataFrame) -> DataFrame:
    """Means over roots of all counters of whole runs, by method."""
    names = ["residual_updates", "push_iterations", "push_cost", "repair_abs", "entries", "rerouted", "broken", "seconds"]
    return trace.where("seq is null").groupBy("method").agg(*(F.avg(c).alias(c) for c in names))


def curve(trace: DataFrame, what: str = "push_cost") -> DataFrame:
    """(method, points, slope, intercept, r2): the line through the mean over roots of a counter after each marked update."""
    at = trace.where("seq is not null").groupBy("method", "seq").agg(F.avg(what).alias("y"))
    fit = [F.regr_slope("y", "seq").alias("slope"), F.regr_intercept("y", "seq").alias("intercept"), F.regr_r2("y", "seq").alias("r2")]
    return at.groupBy("method").agg(F.count("*").alias("points"), *fit)


def median_l1(states: DataFrame, truth: DataFrame) -> DataFrame:
    """(method, l1_error): median over roots of the l1 distance between the estimates of each method's states and ``truth`` (root, node, est)."""
    names = states.select("method").distinct()  # a row a method
    want = truth.where(F.col("node") != SINK).select("root", "node", (-F.col("est")).alias("x")).join(F.broadcast(names))
    both = states.where(F.col("node") != SINK).select("method", "root", "node", F.col("est").alias("x")).unionByName(want)
    gap = both.groupBy("method", "root", "node").agg(F.abs(F.sum("x")).alias("gap"))
    return gap.groupBy("method", "root").agg(F.sum("gap").alias("l1")).groupBy("method").agg(F.percentile("l1", 0.5).alias("l1_error"))


def ratios(tidy: DataFrame, of: str, to: str) -> DataFrame:
    """Rows (graph, method "of / to", metric, value) of a report's rows: quotients of two methods where both have a metric."""
    a, b = (tidy.where(F.col("method") == m) for m in (of, to))
    j = a.join(b.select("graph", "metric", F.col("value").alias("under")), ["graph", "metric"]).where("under <> 0")
    return j.select("graph", F.lit(f"{of} / {to}").alias("method"), "metric", F.round(F.col("value") / F.col("under"), 6).alias("value"))

def extrapolate(seconds: float, first: int, total: int) -> float:
    """Cost of rebuilding after all updates from the cost of the first ones."""
    return seconds / first * total


def symmetry(ppr: DataFrame, degrees: DataFrame) -> DataFrame:
    """(a, b, lhs, rhs): ppr(a,b) d(a) and ppr(b,a) d(b); equal on undirected graphs."""
    d = degrees.select("node", "d_out")
    x = ppr.join(d.withColumnRenamed("node", "root"), "root").select(F.col("root").alias("a"), F.col("node").alias("b"), (F.col("ppr") * F.col("d_out")).alias("lhs"))
    return x.join(x.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("lhs").alias("rhs")), ["a", "b"])


def static_mass(state: DataFrame, degrees: DataFrame, kind: str) -> DataFrame:
    """(root, mass): alpha * rmax * the cost bound of a push from scratch. Forward: residual mass spent; reverse, on undirected
    graphs: the target's degree less the residuals' mass by degree (the potential is the degree there)."""
    j = state.where(F.col("node") != SINK).join(degrees.select("node", "d_out"), "node", "left")
    d = F.coalesce("d_out", F.lit(0))
    mass = 1 - F.sum("res") if kind == "forward" else F.max(F.when(F.col("node") == F.col("root"), d)) - F.sum(d * F.col("res"))
    return j.groupBy("root").agg(mass.alias("mass"))


def drift(old: DataFrame, new: DataFrame, at: DataFrame, degrees: DataFrame, alpha: float = 0.2) -> DataFrame:
    """(root, l1, bound, kept): change of each root's scores by one new arc out of the vertex in ``at`` (src, one row), and its bound."""
    gap = F.abs(F.coalesce("ppr", F.lit(0.0)) - F.coalesce("ppr2", F.lit(0.0)))
    l1 = old.join(new.withColumnRenamed("ppr", "ppr2"), ["root", "node"], "full").groupBy("root").agg(F.sum(gap).alias("l1"))
    here = old.join(at.select(F.col("src").alias("node")), "node").join(degrees.select("node", "d_out"), "node")
    bound = here.select("root", (2 * F.col("ppr") / (alpha * F.col("d_out"))).alias("bound"))
    j = l1.join(bound, "root", "left").na.fill(0.0, ["bound"])
    return j.select("root", "l1", "bound", (F.col("l1") <= F.col("bound") + 1e-12).alias("kept"))


def repair_mass(old: DataFrame, new: DataFrame, batch: DataFrame, degrees: DataFrame, n: int, alpha: float, rmax: float) -> DataFrame:
    """(node, mass, bound, kept): residual that a reverse repair changed at each source of ``batch`` (new arcs) over all n targets."""
    ends = batch.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("k")).join(degrees.select("node", "d_out"), "node", "left")
    both = old.select("root", "node", (-F.col("res")).alias("x")).union(new.select("root", "node", "res")).join(ends.select("node"), "node", "left_semi")
    mass = both.groupBy("root", "node").agg(F.sum("x").alias("x")).groupBy("node").agg(F.sum(F.abs("x")).alias("mass"))
    bound = (2 * n * rmax + 2) / (alpha * (F.col("k") + F.coalesce("d_out", F.lit(0))))
    return mass.join(ends, "node").select("node", "mass", bound.alias("bound"), (F.col("mass") <= bound + 1e-9).alias("kept"))


def forward_static_bound(alpha: float, rmax: float) -> float:
    return 1 / (alpha * rmax)


def forward_update_bound(before: float, after: float, repair: float, alpha: float, rmax: float) -> float:
    """Push cost of one update: residual mass before minus after plus repair mass, over alpha * rmax."""
    return (before - after + repair) / (alpha * rmax)


def reverse_total_bound(n: int, m: int, updates: int, alpha: float, rmax: float, per_target: bool = False) -> float:
    """All targets of an undirected graph: static cost, repairs, and drift of the potential (n times if per_target)."""
    drift = 2 * updates / alpha * (n if per_target else 1)
    return m / (alpha * rmax) + updates * (4 * n / alpha**2 + 4 / (alpha**2 * rmax)) + drift


def pair_score(forward: DataFrame, reverse: DataFrame) -> DataFrame:
    """(s, t, score): a forward state of s and a reverse state of t joined; reverse estimate at s plus forward estimates times reverse residuals."""
    f, r = (x.where(F.col("node") != SINK) for x in (forward, reverse))
    both = f.select(F.col("root").alias("s"), "node", F.col("est").alias("a")).join(r.select(F.col("root").alias("t"), "node", F.col("res").alias("b")), "node")
    own = f.select(F.col("root").alias("s")).distinct().join(r.select(F.col("root").alias("t"), F.col("node").alias("s"), F.col("est").alias("v")), "s")
    parts = both.select("s", "t", (F.col("a") * F.col("b")).alias("v")).union(own.select("s", "t", "v"))
    every = f.select(F.col("root").alias("s")).distinct().crossJoin(F.broadcast(r.select(F.col("root").alias("t")).distinct()))  # roots, not rows
    return every.join(parts.groupBy("s", "t").agg(F.sum("v").alias("v")), ["s", "t"], "left").select("s", "t", F.coalesce("v", F.lit(0.0)).alias("score"))
