"""Hand graphs with known answers, the golden trace, repairs against rebuilt states, and the kernel."""

import random

import numpy as np
import pytest

from driftrank.operators import push, repair
from driftrank.operators.kernel import Local, Walks
from driftrank.sources import graph as G

PATH, TRIANGLE = [(1, 2), (2, 1), (2, 3), (3, 2)], [(1, 2), (2, 1), (2, 3), (3, 2), (1, 3), (3, 1)]


def exact(arcs, alpha=0.2):
    nodes = sorted({x for a in arcs for x in a})
    at = {x: k for k, x in enumerate(nodes)}
    p = np.zeros((len(nodes), len(nodes)))
    for u, v in arcs:
        p[at[u], at[v]] += 1
    d = p.sum(1, keepdims=True)
    p = np.divide(p, d, out=np.zeros_like(p), where=d > 0)
    return nodes, alpha * np.linalg.inv(np.eye(len(nodes)) - (1 - alpha) * p)


def frame(spark, arcs):
    return spark.createDataFrame(arcs, "src long, dst long")


def state_of(df):
    return {r["node"]: (r["est"], r["res"]) for r in df.collect()}


@pytest.mark.parametrize("kind", ["forward", "reverse"])
def test_golden_trace(spark, kind):
    """Push on a path, one edge arrives (both arcs), repair, push again."""
    roots = spark.createDataFrame([(1,)], "root long")
    s = push.push(frame(spark, PATH), push.start_state(roots), 0.2, 0.1, kind)
    got = state_of(s)
    want = {1: (0.331174, 0.083886), 2: (0.369879 if kind == "forward" else 0.184940, 0.0), 3: (0.131174, 0.083886)}
    for k, v in want.items():
        assert got[k] == pytest.approx(v, abs=1e-6)
    batch = spark.createDataFrame([(1, 3, 1), (3, 1, 1)], "src long, dst long, op int")
    old = G.degrees(frame(spark, PATH))
    if kind == "forward":
        fixed = repair.lazy_forward(s, batch, old)
        defect = repair.forward_defect(frame(spark, TRIANGLE), fixed)
        assert state_of(fixed)[1] == pytest.approx((0.662349, -1.047288), abs=1e-6)
    else:
        fixed = repair.reverse(s, batch, old)
        defect = repair.reverse_defect(frame(spark, TRIANGLE), fixed)
        assert state_of(fixed)[3] == pytest.approx((0.131174, 0.376356), abs=1e-6)
    assert max(abs(r["defect"]) for r in defect.collect()) < 1e-12
    end = state_of(push.push(frame(spark, TRIANGLE), fixed, 0.2, 0.1, kind))
    assert end[1] == pytest.approx((0.537195, -0.192122) if kind == "forward" else (0.377476, 0.054797), abs=1e-6)


@pytest.mark.parametrize("how", ["lazy", "eager"])
def test_first_and_last_edge(spark, how):
    """A vertex gets its first out-edge and loses it again: the identity holds, and the state comes back."""
    arcs, roots = frame(spark, [(2, 1)]), spark.createDataFrame([(2,)], "root long")
    s = push.forward(arcs, push.start_state(roots), 0.2, 1e-6)
    assert state_of(s)[-1][0] == pytest.approx(0.64)
    add = spark.createDataFrame([(1, 3, 1)], "src long, dst long, op int")
    both = frame(spark, [(2, 1), (1, 3)])

    def fix(state, batch, graph):
        args = (graph,) if how == "eager" else ()
        return getattr(repair, f"{how}_forward")(state, batch, *args, G.degrees(graph))

    one = fix(s, add, arcs)
    assert max(abs(r["defect"]) for r in repair.forward_defect(both, one).collect()) < 1e-12
    back = state_of(fix(one, add.selectExpr("src", "dst", "-op as op"), both))
    for k, v in state_of(s).items():
        assert back[k] == pytest.approx(v, abs=1e-12)


def test_power_iteration_matches_dense_solve(spark):
    nodes, want = exact(TRIANGLE)
    roots = spark.createDataFrame([(1,)], "root long")
    got = {r["node"]: r["ppr"] for r in push.power_iteration(frame(spark, TRIANGLE), roots, rounds=80).collect()}
    for k, x in enumerate(nodes):
        assert got[x] == pytest.approx(want[0, k], abs=1e-6)


@pytest.mark.parametrize("how", ["lazy", "eager", "reverse"])
@pytest.mark.parametrize("order", ["max_first", "fifo", "sync"])
def test_kernel_toggles(how, order):
    """Random toggles on a directed graph: the exact identity of estimate and residual after every update."""
    rng, edges = random.Random(3), {(0, 1), (1, 2), (2, 0)}
    k = Local(sorted(edges), 0, 0.2, 0.01, "reverse" if how == "reverse" else "forward", order)
    for _ in range(120):
        a = (rng.randrange(6), rng.randrange(6))
        op = -1 if a in edges else 1
        (edges.add if op > 0 else edges.remove)(a)
        k.update([(*a, op)], how)
        nodes, pi = exact([*edges, *((x, x) for x in [])]) if edges else ([0], np.array([[0.2]]))
        at = {x: i for i, x in enumerate(nodes)}
        for t in nodes:
            if how == "reverse":
                if 0 not in at:
                    continue
                value = k.est.get(t, 0) + sum(pi[at[t], at[x]] * r for x, r in k.res.items() if x in at)
                assert value == pytest.approx(pi[at[t], at[0]], abs=1e-9)
            elif 0 in at and all(x in at for x, r in k.res.items() if r):
                value = k.est.get(t, 0) + sum(r * pi[at[x], at[t]] for x, r in k.res.items() if r)
                assert value == pytest.approx(pi[at[0], at[t]], abs=1e-9)
        assert all(abs(r) <= k.limit(u) for u, r in k.res.items())


def test_walks_follow_updates():
    w = Walks(PATH, 1, 0.2, 20000)
    for a in [(1, 3, 1), (3, 1, 1)]:
        w.arc(*a)
    _, pi = exact(TRIANGLE)
    s = w.scores()
    assert max(abs(s[x] - pi[0, k]) for k, x in enumerate([1, 2, 3])) < 0.02
    assert np.mean([len(p) for p in w.paths]) == pytest.approx(5, abs=0.1)


def test_lazy_repair_reads_no_edges(spark):
    """The plan of a lazy repair has no cartesian product and no scan but the state's, the batch's and the degrees'."""
    roots = spark.createDataFrame([(1,)], "root long")
    s = push.start_state(roots)
    batch = spark.createDataFrame([(1, 3, 1)], "src long, dst long, op int")
    plan = repair.lazy_forward(s, batch, G.degrees(frame(spark, PATH)))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastHashJoin" in plan


def test_streaming_maintenance_goes_on_after_a_restart(spark, tmp_path):
    """A file stream with reversed pairs, a loop and nulls, in two runs: the state fits the edges after each, and nothing is applied twice."""
    import datetime

    from driftrank import schemas
    from driftrank.streaming import edges as E

    def put(name, pairs):
        ts = datetime.datetime(2024, 1, 1)
        rows = [(k, ts, u, "x", 1.0, None if v is None else f'{{"k": {v}}}') for k, (u, v) in enumerate(pairs)]
        spark.createDataFrame(rows, schemas.EVENTS).coalesce(1).write.parquet(f"{tmp_path}/in/{name}")

    first = spark.createDataFrame([(13, 22), (22, 13), (21, 21)], "src long, dst long")
    roots = spark.createDataFrame([(13,)], "root long")
    keeper = lambda: E.Maintained(spark, first, roots, f"{tmp_path}/state", rmax=1e-5)
    k = keeper()
    assert {tuple(r) for r in k.edges.collect()} == {(13, 22), (21, 21)} and k.defect() < 1e-12
    for b, rows in enumerate([[(22, 13), (21, 21)], [(13, 30), (30, 13)], [(30, 13), (None, 5), (13, 22), (30, 30)]]):
        k.update(spark.createDataFrame(rows, "src long, dst long"), b)
        assert k.defect() < 1e-12
    want = {(13, 30), (13, 22), (30, 30)}
    assert {tuple(r) for r in k.edges.collect()} == want
    k = keeper()  # the process is gone; its versions are not
    assert k.last == 2 and {tuple(r) for r in k.edges.collect()} == want
    k.update(spark.createDataFrame([(13, 30)], "src long, dst long"), 2)
    assert {tuple(r) for r in k.edges.collect()} == want and len(k.versions()) == 2
    # a real stream, stopped and started again
    put("a", [(1, 2), (3, 2), (None, 1), (4, None)])
    folder, state = f"{tmp_path}/in/*", f"{tmp_path}/stream"
    for run in range(2):
        k = E.Maintained(spark, first.limit(0), roots, state, rmax=1e-5)
        E.maintain_stream(spark, E.read_events(spark, folder), k, f"{tmp_path}/ck")
        assert k.defect() < 1e-12
        if not run:
            assert {tuple(r) for r in k.edges.collect()} == {(13, 22), (22, 29)}
            put("b", [(1, 2), (5, 6)])
    assert {tuple(r) for r in k.edges.collect()} == {(22, 29), (45, 54)}


def test_rates_of_a_stream(spark, tmp_path):
    import datetime

    from driftrank import schemas
    from driftrank.streaming import edges as E

    rows = [(k, datetime.datetime(2024, 1, 1, k // 3), 1, "x", 1.0, "{}") for k in range(12)]
    spark.createDataFrame(rows, schemas.EVENTS).coalesce(1).write.parquet(f"{tmp_path}/in/a")
    q = E.rates(E.read_events(spark, f"{tmp_path}/in/*")).writeStream.format("memory").queryName("rates").outputMode("append").option("checkpointLocation", f"{tmp_path}/ck").trigger(availableNow=True).start()
    q.awaitTermination()
    assert [r["toggles"] for r in spark.table("rates").collect()] and all(r["toggles"] == 3 for r in spark.table("rates").collect())


def test_push_raises_where_it_does_not_settle_and_on_dangling_vertices(spark):
    roots = spark.createDataFrame([(1,)], "root long")
    with pytest.raises(RuntimeError):
        push.push(frame(spark, PATH), push.start_state(roots), 0.2, 1e-12, max_rounds=8)
    with pytest.raises(ValueError):
        push.push(frame(spark, [(1, 2)]), push.start_state(roots), 0.2, 0.1, dangling="error")
    got = state_of(push.push(frame(spark, [(1, 2)]), push.start_state(roots), 0.2, 1e-9, dangling="root"))
    _, pi = exact([(1, 2), (2, 1)])
    assert got[1][0] == pytest.approx(pi[0, 0], abs=1e-7) and got[2][0] == pytest.approx(pi[0, 1], abs=1e-7)


def test_walks_as_rounds(spark):
    """Stop and visit estimates near the exact scores, before and after an edge comes and goes again; walks without a way on are stuck."""
    from driftrank.operators import walks as W

    roots, r = spark.createDataFrame([(1,)], "root long"), 1000
    near = lambda w, how, arcs: max(abs(x["ppr"] - exact(arcs)[1][0, exact(arcs)[0].index(x["node"])]) for x in W.estimate(w, r, how).collect())
    w = W.generate(frame(spark, PATH), roots, r)
    assert near(w, "stop", PATH) < 0.06 and near(w, "visit", PATH) < 0.06 and w.where("stuck").isEmpty()
    more = frame(spark, [(1, 3), (3, 1)])
    w2 = W.reroute_insert(w, more, frame(spark, TRIANGLE))
    assert w2.count() == r and near(w2, "stop", TRIANGLE) < 0.06
    w3 = W.reroute_delete(w2, more, frame(spark, PATH), epoch=2)
    assert w3.count() == r and near(w3, "stop", PATH) < 0.06
    gone = W.reroute_delete(w3, frame(spark, [(2, 1), (2, 3)]), frame(spark, [(1, 2), (3, 2)]), epoch=3)
    assert gone.where("stuck").count() > 0 and gone.where("stuck and element_at(path, -1) <> 2").isEmpty()


def test_rebuild_over_arrays_equals_a_push_from_scratch(spark):
    from driftrank.operators import kernel

    first, events = frame(spark, [(1, 2), (2, 3)]), spark.createDataFrame([(1, 1, 3, 1), (2, 3, 4, 1), (3, 1, 2, -1)], "seq long, src long, dst long, op int")
    end = [(2, 3), (3, 2), (1, 3), (3, 1), (3, 4), (4, 3)]
    for how in ("forward", "reverse"):
        got, trace = kernel.run(first, events, spark.createDataFrame([(2,)], "root long"), [{"name": "a", "how": f"rebuild_{how}", "rmax": 1e-6}])
        got = state_of(got.where("node <> -1"))
        nodes, pi = exact(end)
        for k, x in enumerate(nodes):
            assert got[x][0] == pytest.approx(pi[nodes.index(2), k] if how == "forward" else pi[k, nodes.index(2)], abs=2e-5)
        assert trace.first()["push_iterations"] > 0


def test_kernel_first_state_lists_and_cost_bound():
    """A state from whole-array rounds obeys the stop rule; waiting changes reach lists and sizes; costs keep their bound."""
    from driftrank.operators.kernel import Frozen, Lists

    arcs = [(u, v) for u in range(12) for v in range(12) if u != v and (u * 7 + v * 3) % 5 < 2]
    arcs += [(v, u) for u, v in arcs if (v, u) not in set(arcs)]
    base = Frozen(arcs)
    side = Lists(base, "out")
    side.change(3, 99, 1)
    side.change(99, 3, 1)
    assert side.size(3) == base.size("out", 3) + 1 and side.size(99) == 1 and side.size(100) == 0
    assert sorted(side[3]) == sorted([*base.near("out", 3), 99]) and side[99] == [3]
    for kind in ("forward", "reverse"):
        k = Local(base, 3, 0.2, 1e-4, kind, ready=True)
        assert k.pushes == 0 and not any(k.over(u, s) for u in k.res for s in (1, -1))
    for how in ("lazy", "eager"):
        k = Local(base, 3, 0.2, 1e-4, "forward", ready=True)
        assert all(k.checked_update([(u, 20 + i, 1), (20 + i, u, 1)], how) for i, u in enumerate((3, 4, 5, 3)))
