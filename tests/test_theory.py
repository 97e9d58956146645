"""Measures, orders, counted pushes, dense scores and the keyed stream against plain Python."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from driftrank.functions import measures
from driftrank.operators import exact, kernel, push
from driftrank.sources import graph as G
from driftrank.streaming import edges


def arcs_of(spark, pairs):
    return spark.createDataFrame(list(pairs), "src long, dst long")


def test_dense_solve_of_a_cycle_and_its_bound(spark):
    arcs = arcs_of(spark, [(1, 2), (2, 1)])
    roots = spark.createDataFrame([(1,), (9,)], "root long")
    got = {(r["root"], r["node"]): r["ppr"] for r in exact.dense_solve(arcs, roots).collect()}
    assert got == pytest.approx({(1, 1): 0.2 / (1 - 0.64), (1, 2): 0.16 / (1 - 0.64)})  # a root without arcs has no row
    with pytest.raises(ValueError):
        exact.dense_solve(arcs, roots, limit=1)


def test_counted_pushes_end_like_push_and_keep_the_bound(spark):
    edges_ = [(1, 2), (2, 3), (3, 1), (3, 4)]
    arcs = arcs_of(spark, edges_ + [(b, a) for a, b in edges_])
    start = push.start_state(spark.createDataFrame([(1,), (4,)], "root long"))
    for kind in ("forward", "reverse"):
        state, cost = push.counted(arcs, start, 0.2, 1e-2, kind)
        want = push.push(arcs, start, 0.2, 1e-2, kind)
        a, b = ({(r["root"], r["node"]): (r["est"], r["res"]) for r in x.where("node <> -1").collect()} for x in (state, want))
        assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k], abs=1e-12) for k in a)
        mass = {r["root"]: r["mass"] for r in measures.static_mass(state, G.degrees(arcs), kind).collect()}
        for r in cost.collect():
            assert 0 < r["pushes"] <= r["cost"] and r["cost"] * 0.2 * 1e-2 <= mass[r["root"]] + 1e-9


def test_ranked_orders_by_slice_key_and_ends(spark):
    rows = [(random.Random(i).randrange(5), i, i % 3) for i in range(40)]
    keyed = spark.createDataFrame(rows, "src long, dst long, key long").withColumn("slice", F.struct("key", "src"))
    got = {(r["src"], r["dst"]): r["pos"] for r in G.ranked(keyed).collect()}
    assert got == {(s, d): i + 1 for i, (s, d, _) in enumerate(sorted(rows, key=lambda x: (x[2], x[0], x[1])))}


def test_l1_curve_and_ratios(spark):
    states = spark.createDataFrame([("a", 1, 1, 0.5, 0.0), ("a", 1, -1, 9.0, 0.0), ("a", 2, 2, 1.0, 0.0)], "method string, root long, node long, est double, res double")
    truth = spark.createDataFrame([(1, 1, 0.25), (1, 7, 0.25), (2, 2, 1.0)], "root long, node long, est double")
    assert measures.median_l1(states, truth).first()["l1_error"] == pytest.approx(0.25)  # of 0.5 and 0
    trace = spark.createDataFrame([("a", r, s, 3 * s + r) for r in (0, 2) for s in (1, 2, 3)] + [("a", 0, None, 99)], "method string, root long, seq long, push_cost long")
    fit = measures.curve(trace).first()
    assert (fit["points"], fit["slope"], fit["intercept"], fit["r2"]) == pytest.approx((3, 3.0, 1.0, 1.0))
    tidy = spark.createDataFrame([("g", "a", "x", 6.0), ("g", "b", "x", 3.0), ("g", "a", "y", 1.0), ("g", "b", "y", 0.0)], "graph string, method string, metric string, value double")
    assert [tuple(r) for r in measures.ratios(tidy, "a", "b").collect()] == [("g", "a / b", "x", 2.0)]


def test_marks_of_a_kernel_run(spark):
    first = arcs_of(spark, [(1, 2), (2, 3)])
    later = spark.createDataFrame([(i, 1, 3 + i, 1) for i in range(1, 11)], "seq long, src long, dst long, op int")
    _, trace = kernel.run(first, later, spark.createDataFrame([(1,)], "root long"), [{"name": "r", "how": "reverse", "rmax": 1e-4, "marks": 5}])
    rows = sorted(trace.collect(), key=lambda r: (r["seq"] is None, r["seq"]))
    assert [r["seq"] for r in rows] == [2, 4, 6, 8, 10, None]
    costs = [r["push_cost"] for r in rows]
    assert costs == sorted(costs) and costs[-2] == costs[-1]
    assert measures.summary(trace).first()["push_cost"] == costs[-1]


def test_keyed_stream_of_toggles_goes_on_after_a_restart(spark, tmp_path):
    rng = np.random.default_rng(3)
    rows = [(i, i // 2, int(rng.integers(3)), int(rng.integers(2))) for i in range(60)]
    log, out, want, here = str(tmp_path / "log"), str(tmp_path / "out"), {}, {}
    for part in (rows[:25], rows[25:]):
        df = spark.createDataFrame([(s, a, b, t) for s, t, a, b in part], "seq long, src long, dst long, t long")
        df.select("seq", "src", "dst", F.timestamp_seconds("t").alias("ts")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema("seq long, src long, dst long, ts timestamp").parquet(str(tmp_path / "in"))
        edges.resolve_stream(stream, out, log)
    for s, _, a, b in rows:
        here[a, b] = not here.get((a, b), False)
        want[s] = 1 if here[a, b] else -1
    assert {r["seq"]: r["op"] for r in spark.read.parquet(out).collect()} == want


def test_keyed_stream_settles_blocks_not_pairs(spark, tmp_path):
    """A state a pair took a call for each of millions of pairs; over two micro-batches the toggles are those of the batch form."""
    raw = [(i, 8 * (i * 7 % 90) + 5, 8 * (i * 3 % 5) + 6, 1000 + i // 2) for i in range(700)]
    for k, part in enumerate((raw[:400], raw[400:])):
        spark.createDataFrame(part, "seq long, src long, dst long, ts long").coalesce(1).write.parquet(str(tmp_path / f"in{k}"))
        spark.read.parquet(str(tmp_path / f"in{k}")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema("seq long, src long, dst long, ts long").parquet(str(tmp_path / "in"))
        edges.resolve_stream(stream, str(tmp_path / "out"), str(tmp_path / "log"))
    got = {tuple(r) for r in spark.read.parquet(str(tmp_path / "out")).select("seq", "src", "dst", "op").collect()}
    want = {tuple(r) for r in G.resolve_toggles(spark.createDataFrame(raw, "seq long, src long, dst long, ts long")).drop("ts").collect()}
    assert got == want
    assert spark.read.format("statestore").load(str(tmp_path / "log")).count() == 2  # 90 vertices; a state a pair: 90
