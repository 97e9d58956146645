"""Queries of the cost bounds, drift identities, arrival orders and baselines: (DataFrame query, DuckDB SQL or None) by name."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.engine import cut_lineage, shared_folder
from driftrank.functions import measures
from driftrank.operators import exact, kernel, push, repair, walks
from driftrank.plans import methods as M
from driftrank.plans import oracle as O
from driftrank.plans import workloads
from driftrank.sources import graph as G
from driftrank.streaming import edges

ALPHA = 0.2


def _fixed(df: DataFrame, *names: str, digits: int = 6) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) + F.lit(0.0) for n in names})


# --- costs of pushes from scratch and their bounds ---


def _costs(kind: str, rmax: float, k: int = 5):
    """Pushes, their cost, and the bound's mass (cost bound times alpha times rmax) of each root."""

    def query(spark, sf_dir):
        arcs = cut_lineage(G.undirect(G.build(spark, sf_dir, "g_ps")), "arcs")
        state, cost = push.counted(arcs, push.start_state(G.sample_roots(arcs, k)), ALPHA, rmax, kind)
        mass = measures.static_mass(state, G.degrees(arcs), kind)
        j = cost.join(mass, "root")
        return j.select("root", "pushes", "cost", (F.round("mass", 4) + F.lit(0.0)).alias("mass"), (F.col("cost") * ALPHA * rmax <= F.col("mass") + 1e-9).alias("kept"))

    thr = "greatest(coalesce(d, 1), 1)" if kind == "forward" else "1"
    every = " union all ".join(f"select * from x{i}" for i in range(24))
    mass = "1 - sum(res)" if kind == "forward" else "max(case when node = root then d end) - sum(d * res)"
    sql = f"""with {O.arcs('g_ps')}, {O.rounds(O.start(k), [(1, 24)], ALPHA, rmax, kind, 'x')},
        cost as (select root, count(*) as pushes, sum(d)::bigint as cost from ({every}) left join deg using (node) where res > {rmax!r} * {thr} group by 1),
        mass as (select root, {mass} as mass from x_end left join deg using (node) group by 1)
        select root, pushes, cost, round(mass, 4) + 0.0 as mass, cost * {ALPHA * rmax!r} <= mass + 1e-9 as kept from cost join mass using (root)"""
    return query, sql


# --- drift of scores and of the potential ---


def _last_arc_sql(graph: str) -> str:
    """CTEs arcs, deg before the last arrival of a directed graph, arcs2, deg2 after it, new (that arc)."""
    return f"""allof as materialized (select src::bigint as src, dst::bigint as dst, row_number() over (order by md5('1:' || src || ':' || dst) desc, src desc, dst desc) as back from ({O.GRAPHS[graph]})),
        arcs as materialized (select src, dst from allof where back > 1), arcs2 as materialized (select src, dst from allof), new as materialized (select src, dst from allof where back = 1),
        deg as materialized (select src as node, count(*) as d from arcs group by 1), deg2 as materialized (select src as node, count(*) as d from arcs2 group by 1)"""


def _drift(spark, sf_dir):
    """l1 change of each root's scores by one arrival u -> v, against 2 score(root, u) / (alpha new degree of u).

    It holds for series cut after the same number of rounds, too.
    """
    order = cut_lineage(G.permutation(G.build(spark, sf_dir, "g_next")), "order")
    n = order.count()
    old, new = order.where(F.col("pos") < n).select("src", "dst"), order.select("src", "dst")
    at = order.where(F.col("pos") == n).select("src")
    who = cut_lineage(G.sample_roots(old, 5), "roots")
    a, b = (cut_lineage(push.power_iteration(x, who, ALPHA, 16)) for x in (old, new))
    return _fixed(measures.drift(a, b, at, G.degrees(new), ALPHA), "l1", "bound")


def _drift_sql() -> str:
    return f"""with {_last_arc_sql('g_next')}, {O.rounds(O.start(5), [(1, 16)], ALPHA, 0.0, 'forward', 'x')}, {O.rounds(O.start(5), [(1, 16)], ALPHA, 0.0, 'forward', 'y', 'arcs2', 'deg2')},
        gap as (select root, sum(abs(coalesce(x_end.est, 0) - coalesce(y_end.est, 0))) as l1 from x_end full join y_end using (root, node) group by 1),
        lim as (select r.root, 2 * coalesce(x.est, 0) / ({ALPHA} * d) as bound from (select distinct root from x_end) r cross join new join deg2 on deg2.node = new.src left join x_end x on x.root = r.root and x.node = new.src)
        select root, round(l1, 6) + 0.0 as l1, round(bound, 6) + 0.0 as bound, l1 <= bound + 1e-12 as kept from gap join lim using (root)"""


def _arrival_ratio(spark, sf_dir):
    """Potential over degree at the source of an arc, over all arcs: what the last arrival of a random order expects (one)."""
    arcs = cut_lineage(G.build(spark, sf_dir, "g_next"), "arcs")
    j = arcs.join(push.potential(arcs).withColumnRenamed("node", "src"), "src").join(G.degrees(arcs).select(F.col("node").alias("src"), "d_out"), "src")
    ratio = F.col("phi") / F.col("d_out")
    return j.agg(F.count("*").alias("arcs"), F.round(F.avg(ratio), 6).alias("mean"), F.round(F.max(ratio), 4).alias("most"))


def _potential_step(spark, sf_dir):
    """l1 change of the potential by one more edge of an undirected graph: two."""
    first, whole, _ = M.snapshots(spark, sf_dir, "g_geo", 1)
    a, b = (push.potential(x).where("node <> -1") for x in (first, whole))
    gap = F.abs(F.coalesce("phi", F.lit(0.0)) - F.coalesce("phi2", F.lit(0.0)))
    return a.join(b.withColumnRenamed("phi", "phi2"), "node", "full").agg(F.round(F.sum(gap), 4).alias("step"))


# --- repairs and sign phases ---


def _repair_mass(spark, sf_dir, rmax=1e-2):
    """Residual that one edge's arrival adds at its ends, over the reverse states of all targets, and its bound."""
    first, _, late = M.snapshots(spark, sf_dir, "g_geo", 1)
    targets = first.select(F.col("src").alias("root")).distinct()
    state = push.push(first, push.start_state(targets), ALPHA, rmax, "reverse")
    new = repair.reverse(state, late.withColumn("op", F.lit(1)), G.degrees(first), ALPHA)
    return _fixed(measures.repair_mass(state, new, late, G.degrees(first), targets.count(), ALPHA, rmax), "mass", "bound")


def _repair_mass_sql(rmax=1e-2) -> str:
    start = "select node as root, node, 0.0::double as est, 1.0::double as res from deg"
    return f"""with {M.snapshots_sql('g_geo', 1)}, {O.rounds(start, [(1, 24)], ALPHA, rmax, 'reverse', 'x')}, {M.CHANGE.format('deg', 'deg2')},
        delta as ({M.REPAIRS['reverse'].format(1, 'arcs')})
        select node, round(mass, 6) + 0.0 as mass, round(bound, 6) + 0.0 as bound, mass <= bound + 1e-9 as kept from
        (select node, sum(abs(res)) as mass, (2 * (select count(*) from deg) * {rmax!r} + 2) / ({ALPHA} * any_value(d_new)) as bound from delta join chg on u = node group by 1)"""


def _phases(spark, sf_dir, rmax=1e-4):
    """After deletions: estimates only rise in the positive phase and only fall in the negative one, which lifts nothing over the threshold."""
    first, whole, late = M.snapshots(spark, sf_dir, "g_ps", 100)
    who = cut_lineage(G.sample_roots(first, 4), "roots")
    state = push.push(whole, push.start_state(who), ALPHA, rmax)
    s0 = cut_lineage(repair.lazy_forward(state, late.withColumn("op", F.lit(-1)), G.degrees(whole), ALPHA))
    s1 = push.push(first, s0, ALPHA, rmax, signs=(1,))
    s2 = push.push(first, s1, ALPHA, rmax, signs=(-1,))
    named = [s.where("node <> -1").select("root", "node", F.col("est").alias(f"e{i}"), F.col("res").alias(f"r{i}")) for i, s in enumerate((s0, s1, s2))]
    j = named[0].join(named[1], ["root", "node"], "full").join(named[2], ["root", "node"], "full").na.fill(0.0)
    j = j.join(G.degrees(first).select("node", "d_out"), "node", "left")
    over = F.col("r2") / F.greatest(F.coalesce("d_out", F.lit(1)), F.lit(1))
    out = j.groupBy("root").agg(F.min(F.col("e1") - F.col("e0")).alias("rise"), F.max(F.col("e2") - F.col("e1")).alias("fall"), F.max(over).alias("top"), F.min(over).alias("low"))
    ok = (F.col("rise") >= -1e-15) & (F.col("fall") <= 1e-15) & (F.col("top") <= rmax) & (F.col("low") >= -rmax)
    return _fixed(out.withColumn("kept", ok), "rise", "fall", "top", "low", digits=8)


def _phases_sql(rmax=1e-4) -> str:
    gone = M.REPAIRS["lazy"].format(-1, "arcs2")
    return f"""with {M.snapshots_sql('g_ps', 100)}, {O.rounds(O.start(4), [(1, 24)], ALPHA, rmax, 'forward', 'x', 'arcs2', 'deg2')}, {M.CHANGE.format('deg2', 'deg')},
        fixed as materialized (select root, node, sum(est) as est, sum(res) as res from (select root, node, est, res from x_end union all {gone}) group by 1, 2),
        {O.rounds('select * from fixed', [(1, 16)], ALPHA, rmax, 'forward', 'y')}, {O.rounds('select * from y_end', [(-1, 16)], ALPHA, rmax, 'forward', 'z')},
        j as (select root, node, coalesce(f.est, 0) as e0, coalesce(y.est, 0) as e1, coalesce(z.est, 0) as e2, coalesce(z.res, 0) / greatest(coalesce(d, 1), 1) as over
        from fixed f full join y_end y using (root, node) full join z_end z using (root, node) left join deg using (node) where node <> -1),
        g as (select root, min(e1 - e0) as rise, max(e2 - e1) as fall, max(over) as top, min(over) as low from j group by 1)
        select root, round(rise, 8) + 0.0 as rise, round(fall, 8) + 0.0 as fall, round(top, 8) + 0.0 as top, round(low, 8) + 0.0 as low, rise >= -1e-15 and fall <= 1e-15 and top <= {rmax!r} and low >= -{rmax!r} as kept from g"""


# --- walks ---


def _reroutes(before, after, late, arcs):
    """Walks of each root that an insertion moved, and the sum of their chances over visits (no more are expected)."""
    k = late.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("k"))
    d = arcs.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("d"))
    ends = before.select("root", "walk_id", F.size("path").alias("n"), "stuck")
    at = walks.index(before).join(k, "node").join(d, "node").join(ends, ["root", "walk_id"]).where((F.col("pos") < F.col("n") - 1) | F.col("stuck"))
    chance = at.groupBy("root").agg(F.sum(F.col("k") / F.col("d")).alias("expected"))
    old = before.select("root", "walk_id", F.col("path").alias("was"))
    moved = after.join(old, ["root", "walk_id"]).groupBy("root").agg(F.count_if(F.col("path") != F.col("was")).alias("rerouted"))
    j = moved.join(chance, "root", "left").na.fill(0.0, ["expected"])
    return _fixed(j.select("root", "rerouted", "expected", (F.col("rerouted") <= F.col("expected") + 4 * F.sqrt("expected") + 1).alias("kept")), "expected")


REROUTES_SQL = """, chance as (select v.root, sum(s.k / q.d::double) as expected from vis v join (select src, count(*) as k from bat group by 1) s on s.src = v.node join deg2 q on q.node = v.node where (pos < n - 1 or stuck) group by 1),
    moved as (select root, count(c.pos) as rerouted from paths left join cuts c using (root, walk_id) group by 1)
    select root, rerouted, round(coalesce(expected, 0), 6) + 0.0 as expected, rerouted <= coalesce(expected, 0) + 4 * sqrt(coalesce(expected, 0)) + 1 as kept from moved left join chance using (root)"""


# --- baselines ---


def _dense(spark, sf_dir):
    arcs = cut_lineage(G.build(spark, sf_dir, "g_next"), "arcs")
    return _fixed(exact.dense_solve(arcs, G.sample_roots(arcs, 5), ALPHA), "ppr", digits=5)


def _rebuild(kind: str, rmax: float, first: int = 3):
    """States of the rebuild baseline after ``first`` arrivals."""

    def query(spark, sf_dir):
        start, later = workloads.arrivals(spark, sf_dir, "g_ps", first)
        who = workloads.sampled(start, 2)
        state, _ = kernel.run(start, later, who, [{"name": "rebuild", "how": f"rebuild_{kind}", "rmax": rmax}], ALPHA)
        return _fixed(state.where("node <> -1 and est > 0").select("root", "node", "est", "res"), "est", "res")

    return query, f"""with allof as materialized (select src::bigint as src, dst::bigint as dst, row_number() over (order by md5('1:' || src || ':' || dst), src, dst) as pos from ({O.GRAPHS['g_ps']})),
        half as materialized (select count(*) // 2 as h from allof), e0 as materialized (select src, dst from allof, half where pos <= h), arcs as materialized (select src, dst from e0 union select dst, src from e0),
        e1 as materialized (select src, dst from allof, half where pos <= h + {first}), arcs2 as materialized (select src, dst from e1 union select dst, src from e1),
        deg2 as materialized (select src as node, count(*) as d from arcs2 group by 1), {O.rounds(O.start(2), [(1, 24)], ALPHA, rmax, kind, 'x', 'arcs2', 'deg2')}
        select root, node, {M._r('est', 'est')}, {M._r('res', 'res')} from x_end where est > 0"""


# --- arrival orders and streams ---

ORDERS_SQL = {
    "date": "min(o_orderdate)",
    "degree": "-any_value(d)",
    "id": "any_value(0)",
}


def _orders(spark, sf_dir):
    out = [G.arrival_by(spark, sf_dir, by).select(F.lit(by).alias("by"), "src", "dst", "pos") for by in ORDERS_SQL]
    return out[0].union(out[1]).union(out[2])


def _orders_sql() -> str:
    pairs = "select o_custkey * 8 + 3 as src, l_suppkey * 8 + 4 as dst, o_orderdate from lineitem join orders on l_orderkey = o_orderkey"
    part = "select '{0}' as by, src, dst, row_number() over (order by k, src, dst) as pos from (select src, dst, {1} as k from p join d using (src) group by 1, 2)"
    return f"with p as materialized ({pairs}), d as (select src, count(distinct dst) as d from p group by 1) " + " union all ".join(part.format(*x) for x in ORDERS_SQL.items())


def _streamed_toggles(spark, sf_dir):
    """The toggles as a stream with one bit of state by pair, run until all that is there has been read."""
    at = f"{shared_folder(spark)}/toggles-{uuid.uuid4().hex}"
    edges.resolve_stream(G.pairs_of(edges.read_events(spark, f"{sf_dir}/events.parquet*")), f"{at}/out", f"{at}/log")
    return spark.read.schema("seq long, src long, dst long, op int").parquet(f"{at}/out")


def pairs() -> dict:
    q = {
        "cost_static_forward": _costs("forward", 1e-5),
        "cost_static_reverse": _costs("reverse", 1e-2),
        "drift_pointwise": (_drift, _drift_sql()),
        "arrival_ratio_mean": (_arrival_ratio, f"""with {O.directed('g_next')}, {O.rounds("select 0::bigint as root, dst as node, 0.0::double as est, count(*)::double as res from arcs group by dst", [(1, 24)], ALPHA, 0.0, 'forward', 'x')}
            select count(*) as arcs, round(avg((est + res) / d), 6) as mean, round(max((est + res) / d), 4) as most from arcs join x_end on node = src join deg using (node)"""),
        "potential_step": (_potential_step, f"with {M.snapshots_sql('g_geo', 1)} select round(sum(abs(coalesce(deg.d, 0) - coalesce(deg2.d, 0)))::double, 4) as step from deg full join deg2 using (node)"),
        "repair_mass_reverse": (_repair_mass, _repair_mass_sql()),
        "sign_phases": (_phases, _phases_sql()),
        "walk_reroute_rate": M.rerouted("insert", told=_reroutes, told_sql=REROUTES_SQL),
        "walks_all_sources": M.rerouted("insert", "g_geo", 20, 1 << 30, 8, told=_reroutes, told_sql=REROUTES_SQL),
        "exact_ppr_dense": (_dense, f"with {O.directed('g_next')}, {O.rounds(O.start(5), [(1, 24)], ALPHA, 0.0, 'forward', 'x')} select root, node, {M._r('est + res', 'ppr', 5)} from x_end"),
        "rebuild_reverse": _rebuild("reverse", 1e-3),
        "rebuild_forward": _rebuild("forward", 1e-4),
        "arrival_orders": (_orders, _orders_sql()),
        "toggle_stream_keyed": (_streamed_toggles, "select event_id as seq, src, dst, case when row_number() over (partition by src, dst order by ts, event_id) % 2 = 1 then 1 else -1 end::int as op from (select event_id, ts, user_id * 8 + 5 as src, cast(props->>'$.k' as bigint) * 8 + 6 as dst from events) where src is not null and dst is not null"),
    }
    for graph, by in (("g_next", "random"), ("g_dense", "random"), ("g_dense", "date"), ("g_dense", "degree")):
        q[f"amortization_{graph[2:]}_{by}"] = (lambda s, d, g=graph, b=by: workloads.amortization(s, d, g, b), None)
    return q
