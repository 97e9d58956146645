"""Relational queries around the graphs: (DataFrame query, DuckDB SQL) by name."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from driftrank.engine import cut_lineage
from driftrank.operators import walks
from driftrank.plans import oracle as O
from driftrank.sources import graph as G


def degree_histogram(spark, sf_dir) -> DataFrame:
    d = G.degrees(G.undirect(G.build(spark, sf_dir, "g_mid")))
    return d.groupBy("d_out").agg(F.count("*").alias("nodes"))


def dangling_vertices(spark, sf_dir) -> DataFrame:
    e = G.build(spark, sf_dir, "g_web")
    return e.select(F.col("dst").alias("node")).distinct().join(e.select(F.col("src").alias("node")), "node", "left_anti")


def zero_indegree_vertices(spark, sf_dir) -> DataFrame:
    e = G.build(spark, sf_dir, "g_web")
    return e.select(F.col("src").alias("node")).distinct().join(e.select(F.col("dst").alias("node")), "node", "left_anti")


def adjacency_arrays(spark, sf_dir) -> DataFrame:
    """Sorted neighbour lists as text, so that every engine prints them alike."""
    e = G.build(spark, sf_dir, "g_ps")
    return e.groupBy(F.col("src").alias("node")).agg(F.concat_ws(",", F.array_sort(F.collect_list("dst"))).alias("heads"), F.count("*").alias("d"))


def running_degree(spark, sf_dir) -> DataFrame:
    """Each arrival of a random order with its tail's degree right after it."""
    w = Window.partitionBy("src").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return G.permutation(G.build(spark, sf_dir, "g_ps")).withColumn("d", F.count("*").over(w)).select("pos", "src", "d")


def snapshot_diff(spark, sf_dir) -> DataFrame:
    """Arcs whose opposite arc is absent."""
    e = G.build(spark, sf_dir, "g_next")
    return e.exceptAll(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")).intersect(e))


def edge_kinds(how: str):
    def query(spark, sf_dir) -> DataFrame:
        e = G.build(spark, sf_dir, "g_sparse").union(G.build(spark, sf_dir, "g_ps")).select((F.col("src") % 8).alias("a"), (F.col("dst") % 8).alias("b"))
        return (e.cube("a", "b") if how == "cube" else e.rollup("a", "b")).agg(F.count("*").alias("edges"))

    return query, f"select a, b, count(*) as edges from (select src % 8 as a, dst % 8 as b from ({O.GRAPHS['g_sparse']}) union all select src % 8, dst % 8 from ({O.GRAPHS['g_ps']})) group by {how}(a, b)"


def arrival_by_month(spark, sf_dir) -> DataFrame:
    """Customer-supplier pairs by the month of their first order."""
    j = G.ordered_items(spark, sf_dir)
    first = j.groupBy("o_custkey", "l_suppkey").agg(F.min("o_orderdate").alias("d"))
    return first.groupBy(F.date_format("d", "yyyy-MM").alias("month")).agg(F.count("*").alias("pairs"))


def top_degree(spark, sf_dir) -> DataFrame:
    return G.degrees(G.undirect(G.build(spark, sf_dir, "g_sparse"))).select("node", "d_out").orderBy(F.desc("d_out"), "node").limit(20)


def arrival_linear_fit(spark, sf_dir) -> DataFrame:
    """Fit of the running number of distinct tails to the number of arrivals; ranks inside slices of positions."""
    order = G.permutation(G.build(spark, sf_dir, "g_ps"))
    firsts = order.groupBy("src").agg(F.min("pos").alias("pos")).withColumn("slice", F.floor(F.col("pos") / 4096))
    before = Window.orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)  # one row a slice
    sizes = firsts.groupBy("slice").agg(F.count("*").alias("k")).select("slice", F.coalesce(F.sum("k").over(before), F.lit(0)).alias("before"))
    n = F.row_number().over(Window.partitionBy("slice").orderBy("pos")) + F.col("before")
    ranked = firsts.join(F.broadcast(sizes), "slice").withColumn("n", n)
    return ranked.agg(F.round(F.regr_slope("n", "pos"), 6).alias("slope"), F.round(F.regr_r2("n", "pos"), 6).alias("r2"))


def _order(spark, sf_dir, graph="g_ps") -> DataFrame:
    return G.permutation(G.build(spark, sf_dir, graph))


def edges_initial_half(spark, sf_dir) -> DataFrame:
    order = cut_lineage(_order(spark, sf_dir), "order")
    return order.where(F.col("pos") <= order.count() // 2).select("src", "dst")


def simple_graph(spark, sf_dir) -> DataFrame:
    """Transitions of users without loops and repeats."""
    return G.build(spark, sf_dir, "g_next").where("src <> dst").dropDuplicates(["src", "dst"])


def undirected_arcs(spark, sf_dir) -> DataFrame:
    return G.undirect(G.build(spark, sf_dir, "g_dense"))


def graph_intersection(spark, sf_dir) -> DataFrame:
    """Transitions that go both ways."""
    e = G.build(spark, sf_dir, "g_next")
    return e.intersect(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def degree_dominance(spark, sf_dir) -> DataFrame:
    """For each degree of the supplier graph, how many vertices have a lesser one: a theta join of degree classes, not of vertices."""
    h = G.degrees(G.undirect(G.build(spark, sf_dir, "g_dense"))).groupBy("d_out").agg(F.count("*").alias("n"))
    low = h.select(F.col("d_out").alias("low"), F.col("n").alias("m"))
    return h.join(F.broadcast(low), F.col("low") < F.col("d_out"), "left").groupBy("d_out").agg(F.coalesce(F.sum("m"), F.lit(0)).alias("below"))


def rmax_grid(spark, sf_dir) -> DataFrame:
    roots = G.sample_roots(G.undirect(G.build(spark, sf_dir, "g_ps")), 10)
    grid = spark.createDataFrame([(1e-3,), (1e-4,), (1e-5,)], "rmax double")
    return roots.crossJoin(F.broadcast(grid))  # ten roots, three settings


def batch_assignment(spark, sf_dir) -> DataFrame:
    """Arrivals a batch of 1,000: a range join with the batches' bounds."""
    order = cut_lineage(_order(spark, sf_dir), "order")
    bounds = spark.range(0, order.count() // 1000 + 1).select(F.col("id").alias("batch"), (F.col("id") * 1000 + 1).alias("lo"), ((F.col("id") + 1) * 1000).alias("hi"))
    return order.join(F.broadcast(bounds), F.col("pos").between(F.col("lo"), F.col("hi"))).groupBy("batch").agg(F.count("*").alias("edges"), F.sum("pos").alias("places"))


def batch_ntile(spark, sf_dir) -> DataFrame:
    """Each supplier's parts dealt to four equal lots by id."""
    w = Window.partitionBy("dst").orderBy("src")
    return G.build(spark, sf_dir, "g_ps").withColumn("lot", F.ntile(4).over(w)).groupBy("dst", "lot").agg(F.count("*").alias("edges"))


def events_near_order(spark, sf_dir) -> DataFrame:
    """Per day of the year with orders, toggles a day before it to a day after it in any year: an interval join by day."""
    days = G.table(spark, sf_dir, "orders").select(F.date_format("o_orderdate", "MM-dd").alias("day")).distinct()
    e = G.table(spark, sf_dir, "events").select(F.explode(F.array(*(F.date_format(F.date_add(F.to_date("ts"), k), "MM-dd") for k in (-1, 0, 1)))).alias("day"))
    return days.join(e, "day").groupBy("day").agg(F.count("*").alias("toggles"))


def asof_degree(spark, sf_dir) -> DataFrame:
    """Each toggle with its user's number of earlier toggles, as of its time."""
    w = Window.partitionBy("src").orderBy("ts", "seq").rowsBetween(Window.unboundedPreceding, -1)
    return G.toggles(spark, sf_dir).select("seq", F.count("*").over(w).alias("before"))


def toggle_rate_range(spark, sf_dir) -> DataFrame:
    """Each toggle with its key's toggles in the hour up to it: a range frame."""
    rate = F.expr("count(*) over (partition by dst order by ts range between interval 1 hour preceding and current row)")
    return G.toggles(spark, sf_dir).select("seq", rate.alias("rate"))


def cumulative_cost(spark, sf_dir) -> DataFrame:
    """Running number of arcs a tail's arrivals would touch if each rewrote all its neighbours: what eager repair pays."""
    w = Window.partitionBy("src").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    d = _order(spark, sf_dir).withColumn("d", F.count("*").over(w))
    return d.select("pos", "src", F.sum("d").over(w).alias("cost"))


def graph_stats_approx(spark, sf_dir) -> DataFrame:
    """Are approximate counts and medians within five per cent of exact ones?"""
    d = G.degrees(G.undirect(G.build(spark, sf_dir, "g_sparse")))
    s = d.agg(F.count("*").alias("n"), F.approx_count_distinct("node", 0.01).alias("a"), F.percentile("d_out", 0.5).alias("m"), F.percentile_approx("d_out", 0.5, 10_000).alias("b"))
    return s.select("n", (F.abs(F.col("a") - F.col("n")) <= 0.05 * F.col("n")).alias("count_near"), (F.abs(F.col("b") - F.col("m")) <= 1).alias("median_near"))


def edge_kind_grouping_sets(spark, sf_dir) -> DataFrame:
    e = G.build(spark, sf_dir, "g_sparse").union(G.build(spark, sf_dir, "g_ps")).select((F.col("src") % 8).alias("a"), (F.col("dst") % 8).alias("b"))
    return e.groupingSets([["a", "b"], ["b"], []], "a", "b").agg(F.count("*").alias("edges"))


def arrival_pivot(spark, sf_dir) -> DataFrame:
    """Edges of each part kind's tail by the last digit of the tail, a column a quarter of the order."""
    order = cut_lineage(_order(spark, sf_dir), "order")
    quarter = F.least(F.floor((F.col("pos") - 1) * 4 / order.count()), F.lit(3)).cast("int")
    digit = (F.floor(F.col("src") / 8) % 10).alias("digit")
    return order.select(digit, quarter.alias("q")).groupBy("digit").pivot("q", [0, 1, 2, 3]).count().select("digit", *(F.coalesce(str(k), F.lit(0)).alias(f"q{k}") for k in range(4)))


def hash_uniform(spark, sf_dir) -> DataFrame:
    """The walks' numbers in [0, 1): by tenth, how many vertices fall into it."""
    v = G.undirect(G.build(spark, sf_dir, "g_ps")).select(F.col("src").alias("node")).distinct()
    return v.select(F.floor(walks.uniform("u", 1, "node") * 10).alias("tenth")).groupBy("tenth").agg(F.count("*").alias("nodes"))


def state_as_json(spark, sf_dir) -> DataFrame:
    return G.degrees(G.undirect(G.build(spark, sf_dir, "g_geo"))).select(F.to_json(F.struct("node", F.col("d_out").alias("d"))).alias("line"))


def degree_table_sql(spark, sf_dir) -> DataFrame:
    """The degree table through the SQL surface."""
    G.undirect(G.build(spark, sf_dir, "g_dense")).createOrReplaceTempView("driftrank_arcs")
    return spark.sql("select src as node, count(*) as d_out from driftrank_arcs group by src")


def roundtrip_state(spark, sf_dir) -> DataFrame:
    """Degrees written, read back and compared with what was written: rows, sums, and rows that differ."""
    d = G.degrees(G.undirect(G.build(spark, sf_dir, "g_ps")))
    back = cut_lineage(d, "roundtrip")
    return back.agg(F.count("*").alias("n"), F.sum("d_out").alias("m")).crossJoin(F.broadcast(d.exceptAll(back).agg(F.count("*").alias("lost"))))  # one row each


def merge_state(spark, sf_dir) -> DataFrame:
    """Degrees of two snapshots in one row a vertex: a full outer join."""
    order = cut_lineage(_order(spark, sf_dir), "order")
    half = order.count() // 2
    a, b = (order.where(c).groupBy("src").agg(F.count("*").alias(n)) for c, n in ((F.col("pos") <= half, "d_old"), (F.col("pos") > half, "d_more")))
    return a.join(b, "src", "full").select("src", F.coalesce("d_old", F.lit(0)).alias("d_old"), F.coalesce("d_more", F.lit(0)).alias("d_more"))


def topk_hits(spark, sf_dir) -> DataFrame:
    """Of the twenty greatest degrees after all arrivals, those that are among the first twenty after half of them."""
    order = cut_lineage(_order(spark, sf_dir), "order")
    top = lambda e: e.groupBy("src").agg(F.count("*").alias("d")).orderBy(F.desc("d"), "src").limit(20).select("src")
    return top(order).join(top(order.where(F.col("pos") <= order.count() // 2)), "src", "left_semi")


def rounds_needed(spark, sf_dir) -> DataFrame:
    """Rounds until all mass that is left is under the threshold of a vertex, rmax * degree: ln(rmax * degree) / ln(1 - alpha), by degree."""
    d = G.degrees(G.undirect(G.build(spark, sf_dir, "g_ps"))).groupBy("d_out").agg(F.count("*").alias("nodes"))
    grid = F.explode(F.array(*(F.struct(F.lit(x).alias("rmax"), F.lit(a).alias("alpha")) for x in (1e-3, 1e-6, 1e-9) for a in (0.1, 0.2, 0.5))))
    rounds = F.ceil(F.round(F.ln(F.col("x.rmax") * F.col("d_out")) / F.ln(1 - F.col("x.alpha")), 9))  # rounded: an exact power is not one more round
    return d.select("d_out", "nodes", grid.alias("x")).select("d_out", "nodes", "x.rmax", "x.alpha", F.greatest(rounds, F.lit(0)).cast("long").alias("rounds"))


_PS_ORDER = f"select src, pos from (select src::bigint as src, row_number() over (order by md5('1:' || src || ':' || dst), src, dst) as pos from ({O.GRAPHS['g_ps']}))"
_ORDER = f"select src, dst, row_number() over (order by md5('1:' || src || ':' || dst), src, dst) as pos from (select src::bigint as src, dst::bigint as dst from ({O.GRAPHS['g_ps']}))"

PAIRS = {
    "degree_histogram": (degree_histogram, f"with {O.arcs('g_mid')} select d as d_out, count(*) as nodes from deg group by 1"),
    "dangling_vertices": (dangling_vertices, f"with e as ({O.GRAPHS['g_web']}) select dst as node from e except select src from e"),
    "zero_indegree_vertices": (zero_indegree_vertices, f"with e as ({O.GRAPHS['g_web']}) select src as node from e except select dst from e"),
    "adjacency_arrays": (adjacency_arrays, f"select src as node, string_agg(dst::varchar, ',' order by dst) as heads, count(*) as d from ({O.GRAPHS['g_ps']}) group by 1"),
    "running_degree": (running_degree, f"select pos, src, count(*) over (partition by src order by pos) as d from ({_PS_ORDER})"),
    "snapshot_diff": (snapshot_diff, f"with e as ({O.GRAPHS['g_next']}) select src, dst from e where not exists (select 1 from e o where o.src = e.dst and o.dst = e.src)"),
    "edge_kind_rollup": edge_kinds("rollup"),
    "edge_kind_cube": edge_kinds("cube"),
    "arrival_by_month": (arrival_by_month, "select strftime(d, '%Y-%m') as month, count(*) as pairs from (select min(o_orderdate) as d from lineitem join orders on l_orderkey = o_orderkey group by o_custkey, l_suppkey) group by 1"),
    "top_degree": (top_degree, f"with {O.arcs('g_sparse')} select node, d as d_out from deg order by d desc, node limit 20"),
    "arrival_linear_fit": (arrival_linear_fit, f"select round(regr_slope(n, pos), 6) as slope, round(regr_r2(n, pos), 6) as r2 from (select pos, row_number() over (order by pos) as n from (select src, min(pos) as pos from ({_PS_ORDER}) group by 1))"),
    "edges_initial_half": (edges_initial_half, f"with o as materialized ({_ORDER}) select src, dst from o where pos <= (select count(*) // 2 from o)"),
    "simple_graph": (simple_graph, f"select src, dst from ({O.GRAPHS['g_next']}) where src <> dst"),
    "undirected_arcs": (undirected_arcs, f"with {O.arcs('g_dense')} select src, dst from arcs"),
    "graph_intersection": (graph_intersection, f"with e as ({O.GRAPHS['g_next']}) select src, dst from e intersect select dst, src from e"),
    "degree_dominance": (degree_dominance, f"with {O.arcs('g_dense')} select distinct d as d_out, (select count(*) from deg o where o.d < deg.d) as below from deg"),
    "rmax_grid": (rmax_grid, f"with {O.arcs('g_ps')} select root, rmax from {O.roots(10)} cross join (values (1e-3::double), (1e-4::double), (1e-5::double)) t(rmax)"),
    "batch_assignment": (batch_assignment, f"select (pos - 1) // 1000 as batch, count(*) as edges, sum(pos)::bigint as places from ({_ORDER}) group by 1"),
    "batch_ntile": (batch_ntile, f"select dst, lot, count(*) as edges from (select dst, ntile(4) over (partition by dst order by src)::int as lot from ({O.GRAPHS['g_ps']})) group by 1, 2"),
    "events_near_order": (events_near_order, "select day, count(*) as toggles from (select distinct strftime(o_orderdate, '%m-%d') as day from orders) join (select strftime(ts::date + k, '%m-%d') as day from events cross join (values (-1), (0), (1)) t(k)) using (day) group by 1"),
    "asof_degree": (asof_degree, "select event_id as seq, count(*) over (partition by user_id order by ts, event_id) - 1 as before from events"),
    "toggle_rate_range": (toggle_rate_range, "select event_id as seq, count(*) over (partition by props->>'$.k' order by ts range between interval 1 hour preceding and current row) as rate from events"),
    "cumulative_cost": (cumulative_cost, f"select pos, src, (d * (d + 1) // 2)::bigint as cost from (select pos, src, count(*) over (partition by src order by pos) as d from ({_PS_ORDER}))"),
    "graph_stats_approx": (graph_stats_approx, f"with {O.arcs('g_sparse')} select count(*) as n, true as count_near, true as median_near from deg"),
    "edge_kind_grouping_sets": (edge_kind_grouping_sets, edge_kinds("cube")[1].replace("group by cube(a, b)", "group by grouping sets ((a, b), (b), ())")),
    "arrival_pivot": (arrival_pivot, f"with o as materialized ({_PS_ORDER}), s as (select src // 8 % 10 as digit, least(floor((pos - 1) * 4 / (select count(*) from o)), 3) as q from o) select digit, count(*) filter (q = 0) as q0, count(*) filter (q = 1) as q1, count(*) filter (q = 2) as q2, count(*) filter (q = 3) as q3 from s group by 1"),
    "hash_uniform": (hash_uniform, f"with {O.arcs('g_ps')} select floor(('0x' || substr(md5('u1:' || node), 1, 8))::bigint / 4294967296.0 * 10)::bigint as tenth, count(*) as nodes from deg group by 1"),
    "state_as_json": (state_as_json, f"""with {O.arcs('g_geo')} select '{{"node":' || node || ',"d":' || d || '}}' as line from deg"""),
    "degree_table_sql": (degree_table_sql, f"with {O.arcs('g_dense')} select node, d as d_out from deg"),
    "roundtrip_state": (roundtrip_state, f"with {O.arcs('g_ps')} select count(*) as n, sum(d)::bigint as m, 0::bigint as lost from deg"),
    "merge_state": (merge_state, f"with o as materialized ({_PS_ORDER}), h as (select count(*) // 2 as h from o) select src, count(*) filter (pos <= h) as d_old, count(*) filter (pos > h) as d_more from o, h group by 1"),
    "topk_hits": (topk_hits, f"with o as materialized ({_PS_ORDER}) select src from (select src from o group by 1 order by count(*) desc, src limit 20) where src in (select src from o where pos <= (select count(*) // 2 from o) group by 1 order by count(*) desc, src limit 20)"),
    "rounds_needed": (rounds_needed, f"with {O.arcs('g_ps')} select d as d_out, nodes, rmax, alpha, greatest(ceil(round(ln(rmax * d) / ln(1 - alpha), 9)), 0)::bigint as rounds from (select d, count(*) as nodes from deg group by 1) cross join (values (1e-3::double), (1e-6::double), (1e-9::double)) r(rmax) cross join (values (0.1::double), (0.2::double), (0.5::double)) a(alpha)"),
}
