"""States over a stored graph are those of the kernel's root-by-root form; the driver collects no graph."""

import random

import numpy as np
import pytest

from driftrank.operators import kernel, patches
from driftrank.plans import registry
from driftrank.sources import graph as G

METHODS = [
    *({"name": f"{h}_{o}", "how": h, "rmax": 0.01, "order": o, "check": h != "reverse"} for h in ("lazy", "eager", "reverse") for o in ("max_first", "fifo", "sync")),
    {"name": "signs", "how": "lazy", "rmax": 0.01, "signs": (-1, 1)},
    {"name": "rebuild_forward", "how": "rebuild_forward", "rmax": 0.01, "first": 3},
    {"name": "rebuild_reverse", "how": "rebuild_reverse", "rmax": 0.02, "first": 3},
]


@pytest.fixture(scope="module")
def graph(spark):
    rng = random.Random(5)
    edges = list({(8 * rng.randrange(300), 8 * rng.randrange(300)) for _ in range(1500)})
    edges = [e for e in edges if e[0] <= e[1]]
    half = len(edges) // 2
    first = spark.createDataFrame(edges[:half], "src long, dst long")
    later = spark.createDataFrame([(half + i, *e, 1) for i, e in enumerate(edges[half:])], "seq long, src long, dst long, op int")
    # the last root has no arc at first
    roots = spark.createDataFrame([(edges[0][0],), (edges[1][1],), (8 * 400,)], "root long")
    return first, later, roots


def test_stored_states_equal_the_kernel(spark, graph, monkeypatch):
    want = None
    for stored in (False, True):
        monkeypatch.setattr(patches, "fits", lambda *a, s=stored: s)
        states, trace = kernel.run(*graph, METHODS)
        rows = {(r["method"], r["root"], r["node"]): (r["est"], r["res"]) for r in states.collect() if r["node"] != -1}
        costs = {(r["method"], r["root"]): (r["residual_updates"], r["push_iterations"], r["push_cost"], r["repair_abs"], r["entries"], r["broken"]) for r in trace.collect()}
        if want is None:
            want = rows, costs
    keys = {k for x in (want[0], rows) for k, v in x.items() if max(map(abs, v)) > 1e-15}
    for k in keys:
        assert rows.get(k, (0.0, 0.0)) == pytest.approx(want[0].get(k, (0.0, 0.0)), abs=1e-12), k
    assert costs.keys() == want[1].keys()
    for k in costs:
        assert costs[k] == pytest.approx(want[1][k], rel=1e-9, abs=1e-12), k


def test_the_driver_collects_no_graph(spark, graph, monkeypatch):
    monkeypatch.setattr(patches, "fits", lambda *a: True)
    monkeypatch.setattr(type(graph[0]), "toPandas", lambda self: pytest.fail("rows of the graph on the driver"))
    kernel.run(*graph, METHODS[:1])


def test_fits_by_threshold_and_kind_of_events(graph):
    first, later, _ = graph
    fits = lambda m, e=later, **kw: patches.fits(first, e, [m], 0.2, kw.get("undirected", True), kw.get("batch", 1))
    lazy, reverse = {"how": "lazy", "rmax": 0.01}, {"how": "reverse", "rmax": 0.05}
    assert fits(lazy) and fits(reverse)
    assert not fits(lazy | {"rmax": 1e-6}) and not fits(reverse | {"rmax": 1e-6})
    assert not fits(reverse, undirected=False) and not fits(lazy, batch=2) and not fits(lazy | {"marks": 5}) and not fits({"how": "walks", "r": 5})
    assert not fits(lazy, later.withColumn("op", -later["op"])) and not fits(lazy, later.union(later)) and not fits(lazy, later.drop("seq"))


@pytest.mark.parametrize("name", ["rebuild_forward", "sweep_rmax", "sweep_order", "rebuild_reverse", "sweep_signs", "amortization_dense_degree"])
def test_registered_queries_collect_no_graph(spark, monkeypatch, name):
    monkeypatch.setattr(patches, "fits", lambda *a: True)
    monkeypatch.setattr(type(spark.range(1)), "toPandas", lambda self: pytest.fail("rows of the graph on the driver"))
    assert registry.queries()[name](spark, "/root/testdata/sf0.001").count() > 0


@pytest.mark.parametrize("name", ["cost_bound_forward", "amortization_dense_date", "amortization_dense_random"])
def test_these_collect_no_graph_either(spark, monkeypatch, name):
    test_registered_queries_collect_no_graph(spark, monkeypatch, name)


def test_one_vertex_is_refreshed_as_many_are(spark, graph):
    first, later, roots = graph
    stored = patches.Stored(*patches.store(first, later.select("seq", "src", "dst"), True))
    a, b = (patches.State(patches.Patch(stored), roots.first()[0], 0.2, 0.01, "reverse") for _ in range(2))
    for now in (400, 900, 2000):
        at = np.flatnonzero(~a.kept[: len(a.patch.ids)])
        assert [a.patch.degree_of(i, now) for i in at.tolist()] == a.patch.degree(at, now).tolist()
        a.refresh(at, now)
        for i in at.tolist():
            b.refresh_one(i, now)
        assert (a.res == b.res).all() and (a.held == b.held).all() and a.updates == b.updates > 0
        assert a.repair_abs == pytest.approx(b.repair_abs, rel=1e-12)


def test_lists_are_stored_by_vertex_arrival_and_head(spark, graph):
    first, later, _ = graph
    folder, files = patches.store(first, later.select("seq", "src", "dst"), True)
    _, begin, when, far = patches.Stored(folder, files).part(0)
    for lo, hi in zip(begin.tolist(), begin[1:].tolist()):
        keys = list(zip(when[lo:hi].tolist(), far[lo:hi].tolist()))
        assert keys == sorted(keys)


def test_mean_degree_needs_no_distinct_arcs(spark, monkeypatch):
    apart = spark.createDataFrame([(8 * i + 3, 8 * (i * j % 7) + 4) for i in range(9) for j in range(3)], "src long, dst long").distinct()
    mixed = spark.createDataFrame([(8, 16), (16, 8), (16, 16), (16, 24)], "src long, dst long")
    for e in (apart, mixed):
        for undirected in (True, False):
            want = G.stats(G.undirect(e) if undirected else e).first()["avg_degree"]
            assert G.mean_degree(e, undirected).first()["avg_degree"] == want
    monkeypatch.setattr(G, "undirect", lambda e: pytest.fail("distinct arcs"))
    G.mean_degree(apart, True)
