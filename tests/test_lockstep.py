"""Maintenance of many roots side by side against one root at a time, update by update."""

import random

import numpy as np
import pytest

from driftrank.operators import kernel, lockstep


def changes(seed, n=40, start=90, steps=120):
    rng = random.Random(seed)
    pair = lambda k: tuple(sorted((rng.randrange(k), rng.randrange(k))))
    alive = {p for p in (pair(n) for _ in range(start)) if p[0] < p[1]}
    first, events = sorted(alive), []
    while len(events) < steps:
        if rng.random() < 0.5:
            p = rng.choice(sorted(alive))
            alive.discard(p)
            events.append((*p, -1))
        elif (p := pair(n + 4)) not in alive and p[0] < p[1]:
            alive.add(p)
            events.append((*p, 1))
    return first, events


@pytest.mark.parametrize("how", lockstep.HOWS)
@pytest.mark.parametrize(("undirected", "cells", "batch"), [(True, 1 << 23, 1), (False, 1 << 23, 1), (True, 1, 7)])
def test_same_as_one_root(how, undirected, cells, batch, monkeypatch):
    monkeypatch.setattr(lockstep, "CELLS", cells)  # 1: each root is a group of its own
    first, events = changes(len(how))
    arcs = np.array(first + [(v, u) for u, v in first] * undirected)
    both = [[(u, v, op), (v, u, op)] if undirected else [(u, v, op)] for u, v, op in events]
    base, roots = kernel.Frozen(arcs), [3, 7, 43, 200]  # 43 comes with the events, 200 never has an edge
    kind = "reverse" if how == "reverse" else "forward"
    got = list(lockstep.maintain(base, both, roots, {"how": how, "rmax": 1e-4, "marks": 4}, 0.2, batch))
    for root, (row, est, res, sink) in zip(roots, got, strict=True):
        one = kernel.Local(base, root, 0.2, 1e-4, kind, "sync", ready=True)
        u, p, c = one.updates, one.pushes, one.cost
        for lo in range(0, len(both), batch):
            one.update([a for arcs_of in both[lo : lo + batch] for a in arcs_of], how)
        nodes = {*est, *res, *one.est, *one.res}
        assert max(abs(est.get(x, 0) - one.est.get(x, 0)) + abs(res.get(x, 0) - one.res.get(x, 0)) for x in nodes) < 1e-12
        assert abs(sink - one.sink) < 1e-12
        assert (row["push_iterations"], row["push_cost"]) == (one.pushes - p, one.cost - c)
        # an estimate that cancels out is 0 in one order of summation and 1e-18 in another, which has a repair to write
        assert abs(row["residual_updates"] - (one.updates - u)) <= 4
        assert abs(row["repair_abs"] - one.repair_abs) < 1e-9
        assert row["marks"] and row["marks"][-1]["push_cost"] <= row["push_cost"]


def test_orders_differ_in_cost_and_agree_in_result():
    first, events = changes(5)
    base = kernel.Frozen(np.array(first + [(v, u) for u, v in first]))
    done = []
    for order in ("sync", "fifo", "max_first"):
        one = kernel.Local(base, 3, 0.2, 1e-9, "forward", order)
        for u, v, op in events:
            one.update([(u, v, op), (v, u, op)], "lazy")
        done.append(one)
    for other in done[1:]:
        assert max(abs(done[0].est.get(x, 0) - other.est.get(x, 0)) for x in {*done[0].est, *other.est}) < 1e-6
    assert done[0].pushes != done[1].pushes


def test_an_eager_update_sorts_only_what_it_pushes(monkeypatch):
    """All touched pairs were sorted after each update, which took most of the time of eager repair on dense graphs."""
    sizes = []
    unique = np.unique
    monkeypatch.setattr(lockstep.np, "unique", lambda x, *a, **b: sizes.append(len(x)) or unique(x, *a, **b))
    hub = [(0, v) for v in range(1, 400)]
    base = kernel.Frozen(np.array(hub + [(v, u) for u, v in hub]))
    both = [[(0, v, 1), (v, 0, 1)] for v in range(400, 420)]
    row = next(iter(lockstep.maintain(base, both, [0, 1, 2], {"how": "eager", "rmax": 2.4e-3}, 0.2)))[0]
    assert row["residual_updates"] > 20 * 399 and max(sizes[2:], default=0) < 100  # the first two number the vertices


@pytest.mark.parametrize("kind", ["forward", "reverse"])
def test_rebuilds_go_side_by_side(kind, monkeypatch):
    """One push over all arcs for each root and update took minutes a root; the states are those of such pushes."""
    first, events = changes(9)
    base, roots = kernel.Frozen(np.array(first + [(v, u) for u, v in first])), [3, 7, 43]
    both = [[(u, v, op), (v, u, op)] for u, v, op in events]
    want, alive = {r: [0, 0] for r in roots}, set(first)
    for n, (u, v, op) in enumerate(events[:30]):
        (alive.add if op > 0 else alive.discard)((u, v))
        now = np.array([x for a, b in alive for x in ((a, b), (b, a))])
        for r in roots:
            est, res, _, counts = kernel.settle(now[:, 0], now[:, 1], 50, r, 0.2, 1e-3, kind)
            want[r] = [want[r][0] + int(counts[0]), want[r][1] + int(counts[1])] + [est, res] * (n == 29)
    calls, settle = [], kernel.settle
    monkeypatch.setattr(lockstep, "settle", lambda *a: calls.append(a) or settle(*a))
    monkeypatch.setattr(kernel, "settle", lockstep.settle)
    got = list(lockstep.maintain(base, both, roots, {"how": f"rebuild_{kind}", "rmax": 1e-3, "first": 30}, 0.2))
    assert len(calls) == len(roots)  # the first states
    for r, (row, est, res, _) in zip(roots, got, strict=True):
        assert [row["push_cost"], row["push_iterations"]] == want[r][:2] and row["residual_updates"] == want[r][0]
        assert np.allclose([est.get(x, 0) for x in range(50)], want[r][2]) and np.allclose([res.get(x, 0) for x in range(50)], want[r][3])


def test_walks_draw_once_where_nothing_is_rerouted():
    """A draw for each visit took the time of the walk reports. Reroutes of single arcs come as often as visits over degree."""
    hub = [(0, v) for v in range(1, 101)]
    base = kernel.Frozen(np.array(hub + [(v, u) for u, v in hub]))
    w = kernel.Walks(base, 0, 0.2, 50)
    draws, many = [], 0
    at_zero = lambda w: sum(x == 0 for p in w.paths for x in p[:-1])
    whole = w.rng.random
    for v in range(200, 300):
        before, moved, draws[:] = at_zero(w), w.rerouted, []
        w.rng.random = lambda: draws.append(1) or whole()
        w.arc(0, v, 1)
        assert len(draws) == 1 or w.rerouted > moved
        many += before / (v - 99) - (w.rerouted - moved)
        assert at_zero(w) == w.leave[0] and all(w.at[x] == {i for i, p in enumerate(w.paths) if x in p} for x in w.at)
    assert abs(many) < 40  # about 70 are rerouted
    for v in range(200, 300):
        w.arc(0, v, -1)
        assert not any(p[k : k + 2] == [0, v] for p in w.paths for k in range(len(p)))
        assert all(w.at[x] == {i for i, p in enumerate(w.paths) if x in p} for x in w.at) and at_zero(w) == w.leave[0]
