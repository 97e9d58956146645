"""Registered graph queries and their SQL. Doubles are rounded, with + 0.0 against negative zeros; no query returns times."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.functions import measures
from driftrank.operators import kernel, push, repair
from driftrank.plans import oracle as O
from driftrank.plans import methods, relational, theory, workloads
from driftrank.sources import graph as G

ALPHA = 0.2


def rounded(df: DataFrame, *names: str, digits: int = 6) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) + F.lit(0.0) for n in names})


def _r(expr: str, name: str, digits: int = 6) -> str:
    return f"round({expr}, {digits}) + 0.0 as {name}"


STATE_SQL = f"select root, node, {_r('est', 'est')}, {_r('res', 'res')} from x_end"


def _static(graph: str, kind: str, rmax: float, k: int = 2):
    def query(spark, sf_dir):
        arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, graph)))
        state = push.push(arcs, push.start_state(G.sample_roots(arcs, k)), ALPHA, rmax, kind)
        return rounded(state, "est", "res")

    sql = f"with {O.arcs(graph)}, {O.rounds(O.start(k), [(1, 24)], ALPHA, rmax, kind, 'x')} {STATE_SQL}"
    return query, sql


def _batch_of(spark, sf_dir, graph, n):
    """Arcs without the last ``n`` edges of the order, all arcs, and the batch of the last ones (both ways)."""
    order = push.cut_lineage(G.permutation(G.build(spark, sf_dir, graph)), "order")
    cut = order.count() - n
    first = push.cut_lineage(G.undirect(order.where(F.col("pos") <= cut)), "arcs")
    last = order.where(F.col("pos") > cut).select("src", "dst")
    return first, G.undirect(order), G.undirect(last).withColumn("op", F.lit(1))


def _order_sql(graph: str, n: int) -> str:
    return f"""allof as materialized (select src::bigint as src, dst::bigint as dst, row_number() over (order by md5('1:' || src || ':' || dst), src, dst) as pos from ({O.GRAPHS[graph]})),
    cutoff as materialized (select max(pos) - {n} as c from allof),
    e as materialized (select src, dst from allof, cutoff where pos <= c), arcs as materialized (select src, dst from e union select dst, src from e),
    deg as materialized (select src as node, count(*) as d from arcs group by 1),
    bat as materialized (select src, dst from allof, cutoff where pos > c union select dst, src from allof, cutoff where pos > c),
    arcs2 as materialized (select * from arcs union select * from bat), deg2 as materialized (select src as node, count(*) as d from arcs2 group by 1),
    chg as materialized (select b.src as u, coalesce(d.d, 0)::double as d_old, n.d::double as d_new from (select distinct src from bat) b left join deg d on d.node = b.src join deg2 n on n.node = b.src)"""


#: Rows that each repair adds to the state x_end (root, node, est, res).
REPAIR_SQL = {
    "lazy": f"""select root, node, est / d_old * (d_new - d_old) as est, -est / d_old * (d_new - d_old) / {ALPHA} as res from x_end join chg on node = u where d_old > 0
        union all select root, bat.dst, 0, case when d_old > 0 then est / d_old else est / d_new end * {(1 - ALPHA) / ALPHA!r} from x_end join chg on node = u join bat on bat.src = u
        union all select root, -1, -est * {(1 - ALPHA) / ALPHA!r}, 0 from x_end join chg on node = u where d_old = 0""",
    "eager": f"""select root, arcs2.dst as node, 0.0 as est, est * {(1 - ALPHA) / ALPHA!r} * (1 / d_new - case when o.dst is null then 0 else 1 / d_old end) as res
        from x_end join chg on node = u join arcs2 on arcs2.src = u left join arcs o on o.src = u and o.dst = arcs2.dst
        union all select root, -1, -est * {(1 - ALPHA) / ALPHA!r}, 0 from x_end join chg on node = u where d_old = 0""",
    "reverse": f"""select root, u as node, 0.0 as est, (xn - est + {ALPHA} * unit) / {ALPHA} - res as res from (
        select *, ((case when d_old > 0 then est + {ALPHA} * res - {ALPHA} * unit else 0 end) * d_old + {1 - ALPHA} * heads) / d_new as xn from (
        select r.root, u, d_old, d_new, coalesce(s.est, 0) as est, coalesce(s.res, 0) as res, coalesce(h.heads, 0) as heads, case when u = r.root then 1 else 0 end as unit, s.root is not null or h.root is not null or u = r.root as hit
        from chg cross join (select distinct root from x_end) r left join x_end s on s.root = r.root and s.node = u
        left join (select root, bat.src, sum(est) as heads from bat join x_end on node = bat.dst group by 1, 2) h on h.root = r.root and h.src = u) where hit)""",
}


def _maintained(how: str, graph: str, rmax: float, n: int = 40, again: bool = True, k: int = 2):
    kind = "reverse" if how == "reverse" else "forward"

    def query(spark, sf_dir):
        first, arcs, batch = _batch_of(spark, sf_dir, graph, n)
        batch = push.cut_lineage(batch, "batch")
        state = push.push(first, push.start_state(G.sample_roots(first, k)), ALPHA, rmax, kind)
        old = G.degrees(first)
        if how == "lazy":
            state = repair.lazy_forward(state, batch, old, ALPHA)
        elif how == "eager":
            state = repair.eager_forward(state, batch, first, old, ALPHA)
        else:
            state = repair.reverse(state, batch, old, ALPHA)
        if again:
            state = push.push(arcs, push.cut_lineage(state), ALPHA, rmax, kind)
        return rounded(state, "est", "res")

    sql = f"with {_order_sql(graph, n)}, {O.rounds(O.start(k), [(1, 24)], ALPHA, rmax, kind, 'x')}, fixed as materialized (select root, node, sum(est) as est, sum(res) as res from (select root, node, est, res from x_end union all {REPAIR_SQL[how]}) group by 1, 2)"
    if again:
        sql += f", {O.rounds('select * from fixed', [(1, 16), (-1, 16)], ALPHA, rmax, kind, 'y', 'arcs2', 'deg2')} select root, node, {_r('est', 'est')}, {_r('res', 'res')} from y_end"
    else:
        sql += f" select root, node, {_r('est', 'est')}, {_r('res', 'res')} from fixed"
    return query, sql


def _exact(graph: str, kind: str, k: int = 2):
    def query(spark, sf_dir):
        arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, graph)))
        return rounded(push.power_iteration(arcs, G.sample_roots(arcs, k), ALPHA, 40, kind), "ppr", digits=5)

    sql = f"with {O.arcs(graph)}, {O.rounds(O.start(k), [(1, 40)], ALPHA, 0.0, kind, 'x')} select root, node, {_r('est', 'ppr', 5)} from x_end"
    return query, sql


def _per_edge(spark, sf_dir, how):
    """Every update on its own in the local kernel; estimates of the end state."""
    first, later = workloads.arrivals(spark, sf_dir, "g_geo", 30)
    who = workloads.sampled(first, 2)
    state, _ = kernel.run(first, later, who, [{"name": how, "how": how, "rmax": 1e-9}])
    return rounded(state.where("node <> -1").select("root", "node", "est"), "est", digits=4).where("est > 0")


def _per_edge_sql(how):
    kind = "reverse" if how == "reverse" else "forward"
    return f"""with allof as materialized (select src::bigint as src, dst::bigint as dst, row_number() over (order by md5('1:' || src || ':' || dst), src, dst) as pos from ({O.GRAPHS['g_geo']})),
    half as materialized (select count(*) // 2 as h from allof), e0 as materialized (select src, dst from allof, half where pos <= h),
    arcs as materialized (select src, dst from e0 union select dst, src from e0), r0 as materialized (select * from {O.roots(2)}),
    e1 as materialized (select src, dst from allof, half where pos <= h + 30), arcs2 as materialized (select src, dst from e1 union select dst, src from e1),
    deg2 as materialized (select src as node, count(*) as d from arcs2 group by 1),
    {O.rounds('select root, root as node, 0.0::double as est, 1.0::double as res from r0', [(1, 60)], ALPHA, 0.0, kind, 'x', 'arcs2', 'deg2')} select root, node, {_r('est', 'est', 4)} from x_end where round(est, 4) > 0"""


def _cost_bound(spark, sf_dir):
    """Of 300 single updates, those whose push cost breaks the bound by residual mass and repair mass: none."""
    first, later = workloads.arrivals(spark, sf_dir, "g_dense", 300)
    methods = [{"name": h, "how": h, "rmax": 5e-5, "check": True} for h in ("lazy", "eager")]
    _, trace = kernel.run(first, later, workloads.sampled(first, 4), methods)
    return trace.groupBy("method").agg(F.sum("broken").alias("broken"))


def _phi_sum(spark, sf_dir):
    arcs = push.cut_lineage(G.build(spark, sf_dir, "g_next"))
    return push.potential(arcs).agg(F.round(F.sum("phi"), 2).alias("total"))


def _phi_is_degree(spark, sf_dir):
    arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, "g_geo")))
    return push.potential(arcs).where("node <> -1").select("node", (F.round("phi", 3) + F.lit(0.0)).alias("phi"))


def _degree_table(spark, sf_dir):
    return G.degrees(G.undirect(G.build(spark, sf_dir, "g_dense"))).select("node", "d_out", "d_in")


def _stats(spark, sf_dir):
    out = None
    for g in ("g_sparse", "g_mid", "g_dense", "g_ps"):
        s = G.stats(G.undirect(G.build(spark, sf_dir, g))).withColumn("graph", F.lit(g))
        out = s if out is None else out.union(s)
    return out.select("graph", "n", "m", "avg_degree")


def _top(spark, sf_dir):
    arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, "g_ps")))
    state = push.forward(arcs, push.start_state(G.sample_roots(arcs, 3)), ALPHA, 1e-5)
    return rounded(push.top_k(state, 10), "score")



def _pairs() -> dict:
    q = {}
    for g in O.GRAPHS:
        q[f"edges_{g}"] = (lambda s, d, g=g: G.build(s, d, g), O.GRAPHS[g])
    q["degree_table"] = (_degree_table, f"with {O.arcs('g_dense')} select node, d as d_out, d as d_in from deg")
    q["graph_stats"] = (_stats, " union all ".join(f"(with {O.arcs(g)} select '{g}' as graph, count(*) as n, sum(d)::bigint as m, round(avg(d), 6) as avg_degree from deg)" for g in ("g_sparse", "g_mid", "g_dense", "g_ps")))
    q["random_permutation"] = (lambda s, d: G.permutation(G.build(s, d, "g_ps")), f"select src::bigint as src, dst::bigint as dst, row_number() over (order by md5('1:' || src || ':' || dst), src, dst) as pos from ({O.GRAPHS['g_ps']})")
    q["sample_roots"] = (lambda s, d: G.sample_roots(G.undirect(G.build(s, d, "g_mid")), 100), f"with {O.arcs('g_mid')} select root from {O.roots(100)}")
    q["toggle_ops"] = (lambda s, d: G.resolve_toggles(G.toggles(s, d)).drop("ts"), "select event_id as seq, src, dst, case when row_number() over (partition by src, dst order by ts, event_id) % 2 = 1 then 1 else -1 end::int as op from (select event_id, ts, user_id * 8 + 5 as src, cast(props->>'$.k' as bigint) * 8 + 6 as dst from events)")
    for g, r in (("g_sparse", 5e-5), ("g_mid", 5e-5), ("g_dense", 5e-5)):
        q[f"forward_push_{g[2:]}"] = _static(g, "forward", r)
        q[f"reverse_push_{g[2:]}"] = _static(g, "reverse", 1e-3)
    q["multi_root_push"] = _static("g_ps", "forward", 1e-5, 8)
    q["exact_ppr"], q["exact_ppr_reverse"] = _exact("g_geo", "forward"), _exact("g_geo", "reverse")
    for how in ("lazy", "eager", "reverse"):
        r = 1e-3 if how == "reverse" else 3e-5
        q[f"repair_{how}"] = _maintained(how, "g_dense", r, again=False)
        q[f"maintain_{how}_batch"] = _maintained(how, "g_dense", r)
        q[f"maintain_{how}_per_edge"] = (lambda s, d, h=how: _per_edge(s, d, h), _per_edge_sql(how))
    q["cost_bound_forward"] = (_cost_bound, "select 'lazy' as method, 0::bigint as broken union all select 'eager', 0")
    q["phi_sum"] = (_phi_sum, f"select round(count(*)::double, 2) as total from ({O.GRAPHS['g_next']})")
    q["phi_is_degree"] = (_phi_is_degree, f"with {O.arcs('g_geo')} select node, round(d::double, 3) as phi from deg")
    q |= relational.PAIRS | methods.pairs() | theory.pairs()
    q["topk_ppr"] = (_top, f"with {O.arcs('g_ps')}, {O.rounds(O.start(3), [(1, 24)], ALPHA, 1e-5, 'forward', 'x')} select root, rank, node, {_r('est', 'score')} from (select *, row_number() over (partition by root order by est desc, node) as rank from x_end) where rank <= 10")
    q["table2_report"] = (lambda s, d: workloads.table2(s, d), None)
    q["table3_report"] = (lambda s, d: workloads.table3_4(s, d, k=50, rmax=5e-5, r=16000), None)
    q["table4_report"] = (lambda s, d: workloads.table3_4(s, d, k=100, rmax=2e-5, r=25000), None)
    q["figure1_report"] = (lambda s, d: workloads.figure1(s, d), None)
    q["toggle_report"] = (workloads.toggles, None)
    for what in ("order", "rmax", "signs"):
        q[f"sweep_{what}"] = (lambda s, d, w=what: workloads.sweep(s, d, what=w), None)
    return q


def flagship(spark, sf_dir: str) -> DataFrame:
    """The ten parts and suppliers nearest to a supplier."""
    return _top(spark, sf_dir)


def queries() -> dict:
    return {k: q for k, (q, _) in _pairs().items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in _pairs().items() if s}
