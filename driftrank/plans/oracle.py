"""DuckDB SQL that gives the graph queries' results another way: graphs, orders, and push rounds as chained tables."""

from __future__ import annotations

GRAPHS = {
    "g_sparse": "select distinct l_orderkey * 8 + 1 as src, l_partkey * 8 + 2 as dst from lineitem",
    "g_mid": "select distinct o_custkey * 8 + 3 as src, l_partkey * 8 + 2 as dst from lineitem join orders on l_orderkey = o_orderkey",
    "g_dense": "select distinct o_custkey * 8 + 3 as src, l_suppkey * 8 + 4 as dst from lineitem join orders on l_orderkey = o_orderkey",
    "g_ps": "select distinct l_partkey * 8 + 2 as src, l_suppkey * 8 + 4 as dst from lineitem",
    "g_toggle": "select user_id * 8 + 5 as src, cast(props->>'$.k' as bigint) * 8 + 6 as dst from events group by all having count(*) % 2 = 1",
    "g_next": "select distinct k * 8 + 6 as src, n * 8 + 6 as dst from (select cast(props->>'$.k' as bigint) as k, lead(cast(props->>'$.k' as bigint)) over (partition by user_id order by ts, event_id) as n from events) where n is not null",
    "g_web": """select page_id * 8 + 7 as src, ('0x' || substr(md5(link), 1, 12))::bigint * 8 as dst from (select distinct page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) as link from pages)""",
    "g_geo": """select n_nationkey * 8 + 1 as src, n_regionkey * 8 as dst from nation union select s_suppkey * 8 + 4, s_nationkey * 8 + 1 from supplier
        union select c_custkey * 8 + 3, c_nationkey * 8 + 1 from customer""",
}


def arcs(graph: str, where: str = "") -> str:
    """CTEs e (edges), arcs (both ways), deg."""
    return f"""e as materialized (select src::bigint as src, dst::bigint as dst from ({GRAPHS[graph]}) {where}),
    arcs as materialized (select src, dst from e union select dst, src from e), deg as materialized (select src as node, count(*) as d from arcs group by 1)"""


def directed(graph: str) -> str:
    """CTEs arcs (as they are) and deg."""
    return f"arcs as materialized (select distinct src::bigint as src, dst::bigint as dst from ({GRAPHS[graph]})), deg as materialized (select src as node, count(*) as d from arcs group by 1)"


def roots(k: int, seed: int = 1) -> str:
    return f"(select src as root from (select distinct src from arcs) order by md5('{seed}:' || src), src limit {k})"


def rounds(start: str, plan: list[tuple[int, int]], alpha: float, rmax: float, kind: str, prefix: str, arcs_name: str = "arcs", deg: str = "deg", stuck: str = "") -> str:
    """``stuck``: rows from s that take the mass of vertices without heads. Chained tables {prefix}0.. : synchronous rounds, (sign, count) by phase; the last is {prefix}_end."""
    out, k = [f"{prefix}0 as materialized ({start})"], 0
    thr = "greatest(coalesce(d, 1), 1)" if kind == "forward" else "1"
    for sign, count in plan:
        for _ in range(count):
            far = (
                f"select s.root, a.dst, 0.0, s.res * {1 - alpha!r} / s.d from s join {arcs_name} a on a.src = s.node where s.go"
                if kind == "forward"
                else f"select s.root, a.src, 0.0, s.res * {1 - alpha!r} / q.d from s join {arcs_name} a on a.dst = s.node join {deg} q on q.node = a.src where s.go"
            )
            out.append(f"""{prefix}{k + 1} as materialized (with s as materialized (select p.*, g.d, p.res * {sign} > {rmax!r} * {thr} as go from {prefix}{k} p left join {deg} g using (node))
            select root, node, sum(est) as est, sum(res) as res from (select root, node, est + case when go then {alpha!r} * res else 0 end as est, case when go then 0 else res end as res from s union all {far} {stuck}) group by 1, 2)""")
            k += 1
    return ",\n".join(out) + f",\n{prefix}_end as (select * from {prefix}{k})"


def start(k: int) -> str:
    return f"select root, root as node, 0.0::double as est, 1.0::double as res from {roots(k)}"
