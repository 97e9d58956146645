"""The reports run the published experiments whole."""

import pytest

from driftrank.plans import registry, workloads
from driftrank.sources import graph as G

SF = "/root/testdata/sf0.001"
GRAPH = {"table2_report": "g_dense", "table3_report": "g_dense", "table4_report": "g_dense", "figure1_report": "g_mid", "sweep_order": "g_dense", "sweep_rmax": "g_dense", "sweep_signs": "g_dense"}
SET = {
    "table2_report": {"lazy": 7e-7, "eager": 1e-6},
    "table3_report": {"push": 5e-5, "walks": 16000},
    "table4_report": {"push": 2e-5, "walks": 25000},
    "figure1_report": {"reverse": 1e-4, "rebuild": 1e-4},
}


class Seen(Exception):
    pass


@pytest.mark.parametrize("name", [*GRAPH, "toggle_report"])
def test_reports_take_all_events_roots_and_published_settings(spark, monkeypatch, name):
    def run(initial, events, roots, methods, **kw):
        raise Seen(initial.count(), events.count(), roots.count(), methods)

    monkeypatch.setattr(workloads.kernel, "run", run)
    with pytest.raises(Seen) as got:
        registry.queries()[name](spark, SF)
    initial, events, roots, methods = got.value.args
    if name == "toggle_report":
        assert (initial, events) == (0, G.toggles(spark, SF).count())
    else:
        edges = G.build(spark, SF, GRAPH[name]).count()
        assert (initial, events) == (edges // 2, edges - edges // 2)
    nodes = G.toggles(spark, SF).select("src").distinct().count() if name == "toggle_report" else 100
    assert roots == min(100, nodes)
    for m in methods:
        assert m["name"] not in SET.get(name, {}) or m.get("rmax", m.get("r")) == SET[name][m["name"]]
    if name == "figure1_report":
        assert [m["first"] for m in methods if "first" in m] == [min(1000, events)]
