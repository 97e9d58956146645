"""rounds_needed reads its degrees from a given table."""

from driftrank.operators import push
from driftrank.plans import registry
from driftrank.sources import graph as G

SF = "/root/testdata/sf0.001"


def test_rounds_needed_covers_the_degrees_of_the_table(spark):
    got = registry.queries()["rounds_needed"](spark, SF).collect()
    nodes = G.stats(G.undirect(G.build(spark, SF, "g_ps"))).first()["n"]
    assert sum(r["nodes"] for r in got) == 9 * nodes
    for r in got:
        left, limit = (1 - r["alpha"]) ** r["rounds"], r["rmax"] * r["d_out"]
        assert left <= limit * (1 + 1e-6)
        assert r["rounds"] == 0 or left / (1 - r["alpha"]) > limit * (1 - 1e-6)


def test_power_iteration_takes_only_arcs_in_reach(spark, monkeypatch):
    """Each round joined the lists of the whole graph, also of parts that no root can reach."""
    edges = [(1, 2), (2, 3), (3, 1), (3, 4), (10, 11), (11, 12), (5, 1)]
    arcs = spark.createDataFrame(edges, "src long, dst long")
    roots = spark.createDataFrame([(1,), (12,)], "root long")
    assert {tuple(r) for r in push.within(arcs, roots).collect()} == set(edges[:4])
    want = {tuple(r) for r in push.power_iteration(arcs, roots, 0.2, 8).collect()}
    monkeypatch.setattr(push, "WHOLE", 0)
    took = []
    monkeypatch.setattr(push, "lists", lambda a, kind, f=push.lists: took.append(a.count()) or f(a, kind))
    got = {tuple(r) for r in push.power_iteration(arcs, roots, 0.2, 8).collect()}
    assert took == [4] and {(r, n): round(x, 12) for r, n, x in got} == {(r, n): round(x, 12) for r, n, x in want}
    monkeypatch.setattr(push, "BROADCAST_ROWS", 1)
    assert push.within(arcs, roots).count() == len(edges)
