"""Large graphs take rounds of arrays over a stored graph; they give what the DataFrame rounds give."""

import numpy as np
import pytest
from pyspark.sql import DataFrame

from driftrank.operators import kernel, lockstep, push, slices

EDGES = [(8, 17), (17, 26), (26, 8), (26, 35), (82, 91), (91, 98), (43, 8), (43, 98), (8, 98)]  # 35 and 98 have no out-arc


@pytest.mark.parametrize("kind", ["forward", "reverse"])
@pytest.mark.parametrize("rounds", [0, 1, 9])
def test_array_rounds_give_the_rows_of_dataframe_rounds(spark, monkeypatch, kind, rounds):
    """Rounds over a large graph sent every share of every root through a shuffle."""
    arcs = spark.createDataFrame(EDGES, "src long, dst long")
    roots = spark.createDataFrame([(8,), (98,), (500,)], "root long")  # 500 is no vertex of the graph
    rows = lambda df: {(r["root"], r["node"]): round(r["ppr"], 12) for r in df.collect()}
    want = rows(push.power_iteration(arcs, roots, 0.2, rounds, kind))
    monkeypatch.setattr(push, "SLICED", 0)
    monkeypatch.setattr(slices, "PART", 2)
    monkeypatch.setattr(push, "one_round", lambda *a, **b: pytest.fail("a round of DataFrames"))
    assert rows(push.power_iteration(arcs, roots, 0.2, rounds, kind)) == want


HOWS = ("lazy", "eager", "reverse", "walks")


def test_a_graph_that_is_not_stored_by_vertex_is_not_collected_either(spark, monkeypatch):
    """Walks, marks, deletions and low thresholds took all arcs and events to the driver, which ran out of memory."""
    first = spark.createDataFrame([(8, 17), (17, 26), (26, 8)], "src long, dst long")
    events = spark.createDataFrame([(3, 8, 17, -1), (1, 35, 8, 1), (2, 17, 17, 1), (4, 35, 26, 1)], "seq long, src long, dst long, op int")
    methods = [{"name": h, "how": h, "rmax": 1e-6, "r": 4000} for h in HOWS]
    monkeypatch.setattr(DataFrame, "toPandas", lambda self: pytest.fail("collected"))
    states, trace = kernel.run(first, events, spark.createDataFrame([(8,)], "root long"), methods)
    monkeypatch.undo()
    step = np.zeros((4, 4))  # 8, 17, 26, 35 after all events
    for u, v in ((1, 2), (2, 0), (3, 0), (3, 2)):
        step[u, v] = step[v, u] = 1.0
    step[1, 1] = 1.0
    whole = 0.2 * np.linalg.inv(np.eye(4) - 0.8 * step / step.sum(axis=1, keepdims=True))
    for how in HOWS:
        got = {r["node"]: r["est"] for r in states.where(f"method = '{how}' and node >= 0").collect()}
        want = whole[:, 0] if how == "reverse" else whole[0]
        assert np.allclose([got.get(v, 0.0) for v in (8, 17, 26, 35)], want, atol=0.05 if how == "walks" else 1e-4)
    assert trace.count() == len(HOWS)


def test_updates_name_the_arcs_of_batches(monkeypatch):
    both = [[(1, 2, 1), (2, 1, 1)], [(3, 3, 1)], [(2, 1, -1), (1, 2, -1)]]
    monkeypatch.setattr(lockstep.Updates, "CHUNK", 2)
    up = lockstep.Updates.of(both)
    assert list(up.batches(1)) == both and list(up.batches(2)) == [[*both[0], *both[1]], both[2]]
    assert sorted(zip(*(x.tolist() for x in up.among(np.arange(5)).more()), strict=True)) == [(1, 2), (2, 1), (3, 3)]
