"""Queries of walks, deletions, dangling policies, arriving vertices and measures: (DataFrame query, DuckDB SQL) by name."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.engine import shared_folder
from driftrank.functions import measures
from driftrank.operators import push, repair, walks
from driftrank.plans import oracle as O
from driftrank.sources import graph as G
from driftrank.streaming import edges

ALPHA, R = 0.2, 200
BACK = repr((1 - ALPHA) / ALPHA)


def rounded(df: DataFrame, *names: str, digits: int = 6) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) + F.lit(0.0) for n in names})


def _r(expr: str, name: str, digits: int = 6) -> str:
    return f"round({expr}, {digits}) + 0.0 as {name}"


# --- two snapshots of a graph and the batch between them ---


def snapshots(spark, sf_dir: str, graph: str, last: int, by: str = "order") -> tuple[DataFrame, DataFrame, DataFrame]:
    """Arcs of the first snapshot, arcs of the second, and the pairs (both ways) that only the second has.

    ``by`` order: the ``last`` edges of the random order; node: all edges of the ``last`` greatest vertices.
    """
    every = G.build(spark, sf_dir, graph)
    if by == "order":
        order = push.cut_lineage(G.permutation(every), "order")
        late = order.where(F.col("pos") > order.count() - last).select("src", "dst")
    else:
        new = every.select("src").distinct().orderBy(F.desc("src")).limit(last)
        late = every.join(F.broadcast(new), "src").select("src", "dst")  # ``last`` rows
    late = push.cut_lineage(G.undirect(late), "late")
    whole = push.cut_lineage(G.undirect(every), "arcs")
    return push.cut_lineage(whole.join(late, ["src", "dst"], "left_anti"), "arcs"), whole, late


def snapshots_sql(graph: str, last: int, by: str = "order") -> str:
    """CTEs arcs, deg, heads of the first snapshot, arcs2, deg2, heads2 of the second, bat."""
    late = {
        "order": f"select src, dst from (select src, dst, row_number() over (order by md5('1:' || src || ':' || dst) desc, src desc, dst desc) as n from allof) where n <= {last}",
        "node": f"select src, dst from allof where src in (select distinct src from allof order by src desc limit {last})",
    }[by]
    both = "select src, dst from {0} union select dst, src from {0}"
    out = f"allof as materialized (select distinct src::bigint as src, dst::bigint as dst from ({O.GRAPHS[graph]})), late as materialized ({late}), bat as materialized ({both.format('late')}), arcs2 as materialized ({both.format('allof')}), arcs as materialized (select * from arcs2 except select * from bat)"
    return out + "".join(f", deg{n} as materialized (select src as node, count(*) as d from arcs{n} group by 1), heads{n} as materialized (select src as node, row_number() over (partition by src order by dst) - 1 as k, dst as head from arcs{n})" for n in ("", "2"))


# --- walks ---


def uniform_sql(what: str, *parts: str) -> str:
    """walks.uniform() with seed 1."""
    text = " || ':' || ".join([f"'{what}1'", *parts])
    return f"(('0x' || substr(md5({text}), 1, 8))::bigint / 4294967296.0)"


def walk_sql(name: str, base: str, n: str = "", epoch: int = 0) -> str:
    """Recursive CTE ``name`` (root, walk_id, path, fin) from ``base``; rows with fin > 0 are whole walks (2: stuck)."""
    at = ("root", "walk_id", "len(path)")
    stop, pick = uniform_sql(f"s{epoch}.", *at), uniform_sql(f"n{epoch}.", *at)
    return f"""{name} as (select root, walk_id, path, 0 as fin from ({base}) union all
        select x.root, x.walk_id, case when h.head is null then x.path else list_append(x.path, h.head) end, x.fin from (
        select w.root, w.walk_id, w.path, w.path[-1] as node, case when {stop} < {ALPHA} then 1 when d.d is null then 2 else 0 end as fin,
        case when {stop} < {ALPHA} or d.d is null then -1 else floor({pick} * d.d) end as k from {name} w left join deg{n} d on d.node = w.path[-1] where w.fin = 0) x left join heads{n} h on h.node = x.node and h.k = x.k)"""


def _start_sql(k: int, r: int = R, arcs: str = "arcs") -> str:
    return f"select root, walk_id::int as walk_id, [root] as path from {O.roots(k).replace('from arcs)', f'from {arcs})')}, range(1, {r + 1}) t(walk_id)"


PATHS = "select root, walk_id, array_to_string(path, ',') as path, fin = 2 as stuck from {0} where fin > 0"


def _walked(spark, sf_dir, graph="g_ps", k=3, r=R, undirected=True):
    e = G.build(spark, sf_dir, graph)
    arcs = push.cut_lineage(G.undirect(e) if undirected else e, "arcs")
    return arcs, walks.generate(arcs, G.sample_roots(arcs, k), r, ALPHA)


def as_text(w: DataFrame) -> DataFrame:
    return w.select("root", "walk_id", F.concat_ws(",", "path").alias("path"), "stuck")


def _of_walks(fn, sql: str, graph: str = "g_ps", undirected: bool = True):
    heads = ", heads as materialized (select src as node, row_number() over (partition by src order by dst) - 1 as k, dst as head from arcs)"
    setup = f"with recursive {O.arcs(graph) if undirected else O.directed(graph)}{heads}, {walk_sql('walk', _start_sql(3))}, paths as materialized (select root, walk_id, path, fin = 2 as stuck from walk where fin > 0)"
    return (lambda s, d: fn(_walked(s, d, graph, undirected=undirected)[1])), f"{setup} {sql}"


def rerouted(how: str, graph: str = "g_dense", last: int = 400, k: int = 3, r: int = R, told=None, told_sql: str | None = None):
    """Walks of ``k`` roots rerouted over a batch. ``told`` (walks before, after, batch, arcs after) and ``told_sql`` (CTEs paths, vis,
    cuts) state another result than the walks."""

    def query(spark, sf_dir):
        first, whole, late = snapshots(spark, sf_dir, graph, last)
        before, after = (first, whole) if how == "insert" else (whole, first)
        w = walks.generate(before, G.sample_roots(before, k), r, ALPHA)
        new = walks.reroute_insert(w, late, after, ALPHA) if how == "insert" else walks.reroute_delete(w, late, after, ALPHA)
        return told(w, new, late, after) if told else as_text(new)

    a, b = ("", "2") if how == "insert" else ("2", "")
    visits = "select root, walk_id, stuck, len(path) as n, unnest(path) as node, generate_subscripts(path, 1) - 1 as pos from paths"
    if how == "insert":
        u = uniform_sql("i1.", "root", "walk_id", "pos")
        cuts = f"""select root, walk_id, pos, head, false as halt from (select v.*, s.k, q.d, {u} as u from vis v join (select src, count(*) as k from bat group by 1) s on s.src = v.node join deg{b} q on q.node = v.node where (pos < n - 1 or stuck)) x
            join (select src, row_number() over (partition by src order by dst) - 1 as j, dst as head from bat) h on h.src = x.node and h.j = floor(u * d) where u * d < k"""
    else:
        u = uniform_sql("d1.", "v.root", "v.walk_id", "v.pos")
        cuts = f"""select x.root, x.walk_id, x.pos, h.head, h.head is null as halt from (select v.root, v.walk_id, v.pos, v.node, floor({u} * q.d) as k from vis v join vis t on t.root = v.root and t.walk_id = v.walk_id and t.pos = v.pos + 1
            join bat on bat.src = v.node and bat.dst = t.node left join deg{b} q on q.node = v.node) x left join heads{b} h on h.node = x.node and h.k = x.k"""
    sql = f"""with recursive {snapshots_sql(graph, last)}, {walk_sql('walk', _start_sql(k, r, f'arcs{a}'), a)}, paths as materialized (select root, walk_id, path, fin = 2 as stuck from walk where fin > 0), vis as materialized ({visits}),
        cuts as materialized (select * from ({cuts}) qualify row_number() over (partition by root, walk_id order by pos) = 1)"""
    if told_sql:
        return query, f"{sql} {told_sql}"
    sql += f""",
        {walk_sql('more', "select root, walk_id, list_append(path[1:pos + 1], head) as path from paths join cuts using (root, walk_id) where not halt", b, 1)}
        select root, walk_id, array_to_string(path, ',') as path, stuck from paths where not exists (select 1 from cuts c where c.root = paths.root and c.walk_id = paths.walk_id)
        union all select root, walk_id, array_to_string(path[1:pos + 1], ','), true from paths join cuts using (root, walk_id) where halt union all {PATHS.format('more')}"""
    return query, sql


def _walk_accuracy():
    def query(spark, sf_dir):
        arcs, w = _walked(spark, sf_dir, "g_geo", 3, 2000)
        truth = push.cut_lineage(push.top_k(push.power_iteration(arcs, G.sample_roots(arcs, 3), ALPHA, 40), 10, "ppr"))
        return rounded(measures.accuracy(push.top_k(walks.estimate(w, 2000), 10, "ppr"), truth, 10), "accuracy")

    heads = ", heads as materialized (select src as node, row_number() over (partition by src order by dst) - 1 as k, dst as head from arcs)"
    top = "select root, node from (select *, row_number() over (partition by root order by score desc, node) as n from ({0})) where n <= 10"
    sql = f"""with recursive {O.arcs('g_geo')}{heads}, {O.rounds(O.start(3), [(1, 40)], ALPHA, 0.0, 'forward', 'x')}, {walk_sql('walk', _start_sql(3, 2000))},
        truth as materialized ({top.format('select root, node, est as score from x_end')}), found as materialized ({top.format('select root, path[-1] as node, count(*) as score from walk where fin = 1 group by 1, 2')})
        select t.root, round(count(f.node) / 10.0, 6) + 0.0 as accuracy from truth t left join found f on f.root = t.root and f.node = t.node group by 1"""
    return query, sql


# --- deletions and arriving vertices ---

CHANGE = "chg as materialized (select b.src as u, coalesce(o.d, 0)::double as d_old, coalesce(n.d, 0)::double as d_new from (select distinct src from bat) b left join {0} o on o.node = b.src left join {1} n on n.node = b.src)"
#: What each repair adds to x_end; {0} is the sign of the batch, {1} the old arcs.
REPAIRS = {
    "lazy": f"""select root, node, est / d_old * (d_new - d_old) as est, -est / d_old * (d_new - d_old) / {ALPHA} as res from x_end join chg on node = u where d_old > 0 and d_new > 0
        union all select root, bat.dst, 0, {{0}} * case when d_old > 0 then est / d_old else est / d_new end * {BACK} from x_end join chg on node = u join bat on bat.src = u
        union all select root, -1, case when d_new = 0 then est else -est end * {BACK}, 0 from x_end join chg on node = u where d_old = 0 or d_new = 0""",
    "eager": f"""select root, a.dst as node, 0.0 as est, est * {BACK} * (case when {{0}} > 0 or b.dst is null then 1 / d_new else 0 end - case when {{0}} > 0 and b.dst is not null then 0 else 1 / d_old end) as res
        from x_end join chg on node = u join (select src, dst from {{1}} union select src, dst from bat) a on a.src = u left join bat b on b.src = a.src and b.dst = a.dst
        union all select root, -1, case when d_new = 0 then est else -est end * {BACK}, 0 from x_end join chg on node = u where d_old = 0 or d_new = 0""",
    "reverse": f"""select root, u as node, 0.0 as est, (xn - est + {ALPHA} * unit) / {ALPHA} - res as res from (
        select *, case when d_new > 0 then ((case when d_old > 0 then est + {ALPHA} * res - {ALPHA} * unit else 0 end) * d_old + {{0}} * {1 - ALPHA} * heads) / d_new else 0 end as xn from (
        select r.root, u, d_old, d_new, coalesce(s.est, 0) as est, coalesce(s.res, 0) as res, coalesce(h.heads, 0) as heads, case when u = r.root then 1 else 0 end as unit, s.root is not null or h.root is not null or u = r.root as hit
        from chg cross join (select distinct root from x_end) r left join x_end s on s.root = r.root and s.node = u
        left join (select root, bat.src, sum(est) as heads from bat join x_end on node = bat.dst group by 1, 2) h on h.root = r.root and h.src = u) where hit)""",
}


def _kept_fresh(how: str, op: int, rmax: float, last: int = 40, by: str = "order", again: bool = True, k: int = 2):
    """A pushed state of one snapshot, repaired for the other, and (``again``) pushed there."""
    kind = "reverse" if how == "reverse" else "forward"

    def query(spark, sf_dir):
        first, whole, late = snapshots(spark, sf_dir, "g_dense", last, by)
        old, new = (first, whole) if op > 0 else (whole, first)
        batch = late.withColumn("op", F.lit(op))
        state = push.push(old, push.start_state(G.sample_roots(first, k)), ALPHA, rmax, kind)
        d = G.degrees(old)
        if how == "eager":
            state = repair.eager_forward(state, batch, old, d, ALPHA)
        else:
            state = (repair.lazy_forward if how == "lazy" else repair.reverse)(state, batch, d, ALPHA)
        if again:
            state = push.push(new, push.cut_lineage(state), ALPHA, rmax, kind)
        return rounded(state.where("node <> -1"), "est", "res")

    a, b = ("", "2") if op > 0 else ("2", "")
    sql = f"""with {snapshots_sql('g_dense', last, by)}, {O.rounds(O.start(k), [(1, 24)], ALPHA, rmax, kind, 'x', f'arcs{a}', f'deg{a}')}, {CHANGE.format(f'deg{a}', f'deg{b}')},
        fixed as materialized (select root, node, sum(est) as est, sum(res) as res from (select root, node, est, res from x_end union all {REPAIRS[how].format(op, f'arcs{a}')}) group by 1, 2)"""
    if again:
        sql += f", {O.rounds('select * from fixed', [(1, 16), (-1, 16)], ALPHA, rmax, kind, 'y', f'arcs{b}', f'deg{b}')}"
    return query, sql + f" select root, node, {_r('est', 'est')}, {_r('res', 'res')} from {'y_end' if again else 'fixed'} where node <> -1"


# --- dangling vertices ---


def _dangling(spark, sf_dir, policy):
    arcs = push.cut_lineage(G.build(spark, sf_dir, "g_web"), "arcs")
    return push.push(arcs, push.start_state(G.sample_roots(arcs, 3)), ALPHA, 1e-6, "forward", dangling=policy)


ROOT_EDGE = f"union all select s.root, s.root, 0.0, s.res * {1 - ALPHA!r} from s where s.go and s.d is null"


# --- states against exact scores ---


def _compared(spark, sf_dir, kind="forward", rmax=1e-3, k=5):
    arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, "g_geo")), "arcs")
    who = G.sample_roots(arcs, k)
    state = push.cut_lineage(push.push(arcs, push.start_state(who), ALPHA, rmax, kind))
    return arcs, state, push.cut_lineage(push.power_iteration(arcs, who, ALPHA, 32, kind))


def _compared_sql(kind="forward", rmax=1e-3, k=5) -> str:
    """CTEs x_end (pushed state), t_end (32 rounds of power iteration), both over g_geo."""
    return f"with {O.arcs('g_geo')}, {O.rounds(O.start(k), [(1, 24)], ALPHA, rmax, kind, 'x')}, {O.rounds(O.start(k), [(1, 32)], ALPHA, 0.0, kind, 't')}"


def _errors(spark, sf_dir, kinds=("forward", "reverse")):
    out = []
    for kind, col in ((k, {"forward": "max_by_degree", "reverse": "max_abs"}[k]) for k in kinds):
        arcs, state, truth = _compared(spark, sf_dir, kind)
        d = G.degrees(arcs)
        e = measures.errors(state, truth, d).join(measures.certificate(state, d, kind), "root")
        out.append(e.select(F.lit(kind).alias("kind"), "root", F.round("l1", 6).alias("l1"), F.round(col, 7).alias("error"), F.round("bound", 7).alias("bound"), ((F.col(col) <= 1e-3) & (F.col("bound") <= 1e-3)).alias("kept")))
    return out[0].union(out[-1]).distinct()


def _errors_sql() -> str:
    parts = []
    for kind, scale in (("forward", "coalesce(d, 1)"), ("reverse", "1")):
        parts.append(f"""(select '{kind}' as kind, root, round(sum(gap), 6) as l1, round(max(gap / {scale}), 7) as error, round(max(abs(res) / {scale}), 7) as bound, max(gap / {scale}) <= 1e-3 and max(abs(res) / {scale}) <= 1e-3 as kept
            from (select t.root, t.node, abs(coalesce(x.est, 0) - t.est) as gap, coalesce(x.res, 0) as res, d from {kind}_t t left join {kind}_x x on x.root = t.root and x.node = t.node left join deg on deg.node = t.node) group by 2)""")
    ctes = ", ".join(f"{O.rounds(O.start(5), [(1, 24)], ALPHA, 1e-3, kind, f'{kind[0]}x')}, {O.rounds(O.start(5), [(1, 32)], ALPHA, 0.0, kind, f'{kind[0]}t')}, {kind}_x as (select * from {kind[0]}x_end), {kind}_t as (select * from {kind[0]}t_end)" for kind in ("forward", "reverse"))
    return f"with {O.arcs('g_geo')}, {ctes} {' union all '.join(parts)}"


def _top_accuracy(spark, sf_dir):
    _, state, truth = _compared(spark, sf_dir)
    return rounded(measures.accuracy(push.top_k(state, 10), push.top_k(truth, 10, "ppr"), 10), "accuracy")


def _pair_scores(spark, sf_dir):
    """Score of every pair (s, t) of four roots from a forward state of s and a reverse state of t."""
    arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, "g_ps")), "arcs")
    who = G.sample_roots(arcs, 4)
    f, r = (push.cut_lineage(push.push(arcs, push.start_state(who), ALPHA, x, kind)) for kind, x in (("forward", 1e-4), ("reverse", 1e-2)))
    return measures.pair_score(f, r).select("s", "t", (F.round("score", 6) + F.lit(0.0)).alias("score"))


def _one_round(kind: str):
    def query(spark, sf_dir):
        arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, "g_ps")), "arcs")
        return rounded(push.one_round(push.lists(arcs, kind), push.start_state(G.sample_roots(arcs, 5)), ALPHA, 1e-6, 1, kind), "est", "res")

    return query, f"with {O.arcs('g_ps')}, {O.rounds(O.start(5), [(1, 1)], ALPHA, 1e-6, kind, 'x')} select root, node, {_r('est', 'est')}, {_r('res', 'res')} from x_end"


def _storage(spark, sf_dir):
    _, state, _ = _compared(spark, sf_dir)
    return measures.storage(state)


def _frontier(spark, sf_dir):
    """Rows over the threshold after three rounds: what the fourth round pushes."""
    arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, "g_ps")), "arcs")
    adj, state = push.cut_lineage(push.lists(arcs, "forward"), "lists"), push.start_state(G.sample_roots(arcs, 5))
    for _ in range(3):
        state = push.one_round(adj, state, ALPHA, 1e-5, 1, "forward")
    on = state.join(adj.where("chunk = 0").select("node", "thr"), "node", "left").where(push.active(1, 1e-5))
    return on.groupBy("root").agg(F.count("*").alias("active"))


def _symmetry(spark, sf_dir):
    edges = push.cut_lineage(G.build(spark, sf_dir, "g_ps"), "edges")
    arcs = edges.union(edges.select("dst", "src"))  # distinct as they are: parts are no suppliers
    who = push.cut_lineage(G.sample_roots(arcs, 6), "roots")
    near = push.power_iteration(arcs, who, ALPHA, 40).join(F.broadcast(who.withColumnRenamed("root", "node")), "node", "left_semi")  # six rows
    own = arcs.join(F.broadcast(who), F.col("src") == F.col("root"), "left_semi")  # degrees of the roots alone
    return measures.symmetry(near, G.degrees(own)).select("a", "b", F.round("lhs", 4).alias("lhs"), (F.abs(F.col("lhs") - F.col("rhs")) < 1e-4).alias("same"))


def _degree_sum(spark, sf_dir):
    """Each target's column, cut after 24 rounds (a lower bound), against its degree."""
    arcs = push.cut_lineage(G.undirect(G.build(spark, sf_dir, "g_geo")), "arcs")
    column = push.power_iteration(arcs, G.sample_roots(arcs, 20), ALPHA, 24, "reverse").groupBy("root").agg(F.sum("ppr").alias("total"))
    j = column.join(G.degrees(arcs).withColumnRenamed("node", "root"), "root")
    return j.select("root", F.round("total", 5).alias("total"), F.col("d_out").alias("d"), (F.col("total") <= F.col("d_out") * (1 + 1e-9)).alias("kept"))


def _defects(kind: str):
    def query(spark, sf_dir):
        arcs = push.cut_lineage(G.build(spark, sf_dir, "g_web"), "arcs")
        who = G.sample_roots(arcs, 3) if kind == "forward" else G.sample_roots(arcs.select(F.col("dst").alias("src")), 3)
        state = push.cut_lineage(push.push(arcs, push.start_state(who), ALPHA, 1e-4, kind))
        d = (repair.forward_defect if kind == "forward" else repair.reverse_defect)(arcs, state).where("node <> -1")
        own = state.where("node <> -1").groupBy("root").agg(F.round(F.sum("est"), 6).alias("est"), F.round(F.sum("res"), 6).alias("res"))
        return d.groupBy("root").agg(F.count("*").alias("nodes"), (F.round(F.max(F.abs("defect")), 9) + F.lit(0.0)).alias("defect")).join(own, "root")

    who = O.start(3) if kind == "forward" else O.start(3).replace("select distinct src from arcs", "select distinct dst as src from arcs")
    sent = "join arcs a on a.src = x.node join deg g on g.node = a.src" if kind == "forward" else "join arcs a on a.dst = x.node join deg g on g.node = a.src"
    to = "a.dst" if kind == "forward" else "a.src"
    return query, f"""with {O.directed('g_web')}, {O.rounds(who, [(1, 8)], ALPHA, 1e-4, kind, 'x')},
        parts as (select root, node, est + {ALPHA} * res - case when node = root then {ALPHA} else 0 end as v from x_end union all select x.root, {to}, -{1 - ALPHA} * x.est / g.d from x_end x {sent}),
        summed as (select root, node, sum(v) as v from parts group by 1, 2), own as (select root, round(sum(est), 6) as est, round(sum(res), 6) as res from x_end group by 1)
        select root, count(*) as nodes, round(max(abs(v)), 9) + 0.0 as defect, any_value(est) as est, any_value(res) as res from summed join own using (root) group by 1"""


def _toggle_stream(spark, sf_dir):
    """All toggles in two batches through the stream's keeper: the edges at the end, and whether the state fits them."""
    ev = G.toggles(spark, sf_dir)
    half = ev.agg(F.percentile_approx("seq", 0.5)).first()[0] or 0
    roots = ev.agg(F.min("src").alias("root"))
    keeper = edges.Maintained(spark, ev.select("src", "dst").limit(0), roots, f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}", ALPHA, 1e-3)
    for k, part in enumerate((ev.where(F.col("seq") <= half), ev.where(F.col("seq") > half))):
        keeper.update(part, k)
    return keeper.edges.withColumn("fits", F.lit(keeper.defect() < 1e-12))


def pairs() -> dict:
    visits = "select root, unnest(path) as node from paths"
    q = {
        "walk_paths": _of_walks(as_text, "select root, walk_id, array_to_string(path, ',') as path, stuck from paths"),
        "walk_paths_dangling": _of_walks(as_text, "select root, walk_id, array_to_string(path, ',') as path, stuck from paths", "g_web", False),
        "walk_estimate": _of_walks(lambda w: rounded(walks.estimate(w, R), "ppr"), f"select root, path[-1] as node, {_r(f'count(*) / {R}', 'ppr')} from paths where not stuck group by 1, 2"),
        "walk_estimate_visits": _of_walks(lambda w: rounded(walks.estimate(w, R, "visit"), "ppr"), f"select root, node, {_r(f'count(*) * {ALPHA} / {R}', 'ppr')} from ({visits}) group by 1, 2"),
        "walk_visits": _of_walks(walks.index, "select unnest(path) as node, root, walk_id, (generate_subscripts(path, 1) - 1)::int as pos from paths"),
        "visit_count_map": _of_walks(lambda w: walks.index(w).groupBy("root", "node").agg(F.count("*").alias("n")).groupBy("root").agg(F.map_from_entries(F.collect_list(F.struct("node", "n"))).alias("m")).select("root", F.explode("m").alias("node", "visits")), f"select root, node, count(*) as visits from ({visits}) group by 1, 2"),
        "walk_length_mean": _of_walks(lambda w: w.groupBy("root").agg(F.round(F.avg(F.size("path")), 6).alias("mean")), "select root, round(avg(len(path)), 6) as mean from paths group by 1"),
        "walk_storage": _of_walks(walks.storage, "select root, sum(len(path))::bigint as vertices, (4 * sum(len(path)))::bigint as bytes from paths group by 1"),
        "walk_reroute_insert": rerouted("insert"),
        "walk_reroute_delete": rerouted("delete"),
        "topk_accuracy_walk": _walk_accuracy(),
        "node_arrival": _kept_fresh("lazy", 1, 3e-5, 3, "node"),
        "node_arrival_reverse": _kept_fresh("reverse", 1, 1e-3, 3, "node"),
        "node_removal": _kept_fresh("lazy", -1, 3e-5, 3, "node"),
        "dangling_root_edge": (lambda s, d: rounded(_dangling(s, d, "root"), "est", "res"), f"with {O.directed('g_web')}, {O.rounds(O.start(3), [(1, 64)], ALPHA, 1e-6, 'forward', 'x', stuck=ROOT_EDGE)} select root, node, {_r('est', 'est')}, {_r('res', 'res')} from x_end"),
        "dangling_sink_mass": (lambda s, d: rounded(_dangling(s, d, "sink").where("node = -1").select("root", F.col("est").alias("sink")), "sink"), f"with {O.directed('g_web')}, {O.rounds(O.start(3), [(1, 8)], ALPHA, 1e-6, 'forward', 'x')} select root, {_r('1 - sum(est) - sum(res)', 'sink')} from x_end group by 1"),
        "push_one_round_forward": _one_round("forward"),
        "push_one_round_reverse": _one_round("reverse"),
        "active_frontier": (_frontier, f"with {O.arcs('g_ps')}, {O.rounds(O.start(5), [(1, 3)], ALPHA, 1e-5, 'forward', 'x')} select root, count(*) as active from x_end left join deg using (node) where res > 1e-5 * coalesce(d, 1) group by 1"),
        "push_storage": (_storage, f"{_compared_sql()} select root, n as entries, n * 8 as bytes from (select root, count(*) filter (est <> 0) + count(*) filter (res <> 0) as n from x_end group by 1)"),
        "l1_error_push": (lambda s, d: _errors(s, d, ["forward"]).select("root", "l1"), f"select root, l1 from ({_errors_sql()}) where kind = 'forward'"),
        "median_l1_error": (lambda s, d: _errors(s, d, ["reverse"]).agg(F.round(F.percentile("l1", 0.5), 6).alias("median_l1")), f"select round(median(l1), 6) as median_l1 from ({_errors_sql()}) where kind = 'reverse'"),
        "error_bounds": (_errors, _errors_sql()),
        "topk_accuracy_push": (_top_accuracy, f"""{_compared_sql()}, top as (select 't' as what, root, node from (select *, row_number() over (partition by root order by est desc, node) as n from t_end) where n <= 10 union all select 'x', root, node from (select *, row_number() over (partition by root order by est desc, node) as n from x_end) where n <= 10)
            select t.root, round(count(x.node) / 10.0, 6) + 0.0 as accuracy from (select * from top where what = 't') t left join (select * from top where what = 'x') x on x.root = t.root and x.node = t.node group by 1"""),
        "pair_score": (_pair_scores, f"""with {O.arcs('g_ps')}, {O.rounds(O.start(4), [(1, 24)], ALPHA, 1e-4, 'forward', 'f')}, {O.rounds(O.start(4), [(1, 24)], ALPHA, 1e-2, 'reverse', 'v')}, r0 as {O.roots(4)}
            select s.root as s, t.root as t, round(coalesce((select est from v_end where v_end.root = t.root and v_end.node = s.root), 0) + coalesce((select sum(f.est * v.res) from f_end f join v_end v on v.node = f.node where f.root = s.root and v.root = t.root), 0), 6) + 0.0 as score from r0 s cross join r0 t"""),
        "symmetry": (_symmetry, f"""with {O.arcs('g_ps')}, {O.rounds(O.start(6), [(1, 40)], ALPHA, 0.0, 'forward', 'x')}, m as (select root as a, x_end.node as b, est * d as v from x_end join deg on deg.node = root where x_end.node in (select distinct root from x_end))
            select p.a, p.b, round(p.v, 4) as lhs, abs(p.v - o.v) < 1e-4 as same from m p join m o on o.a = p.b and o.b = p.a"""),
        "prop_degree_sum": (_degree_sum, f"with {O.arcs('g_geo')}, {O.rounds(O.start(20), [(1, 24)], ALPHA, 0.0, 'reverse', 'x')} select root, round(sum(est), 5) as total, any_value(d) as d, sum(est) <= any_value(d) * (1 + 1e-9) as kept from x_end join deg on deg.node = root group by 1"),
        "forward_defect": _defects("forward"),
        "reverse_defect": _defects("reverse"),
        "maintain_toggle_stream": (_toggle_stream, f"select least(src, dst) as src, greatest(src, dst) as dst, true as fits from ({O.GRAPHS['g_toggle']})"),
        "knn_edges": (lambda s, d: G.build(s, d, "g_knn"), """with v as materialized (select vec_id, embedding::double[] as e, sqrt(list_dot_product(embedding::double[], embedding::double[])) as l from embeddings)
            select src, dst from (select a.vec_id as src, b.vec_id as dst, row_number() over (partition by a.vec_id order by round(list_dot_product(a.e, b.e) / (a.l * b.l), 9) desc, b.vec_id) as n from v a join v b on a.vec_id <> b.vec_id) where n <= 5"""),
    }
    for how, rmax in (("lazy", 3e-5), ("eager", 3e-5), ("reverse", 1e-3)):
        q[f"repair_{how}_delete"] = _kept_fresh(how, -1, rmax, again=False)
        q[f"maintain_{how}_delete"] = _kept_fresh(how, -1, rmax)
    return q
