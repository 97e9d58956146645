"""Arrival orders: slices are counted inside each key, not all of them in one task."""

from pyspark.sql import functions as F

from driftrank.sources import graph as G


def _order(spark):
    rows = [(8 * (i % 5) + 3, 8 * i + 4, None if i % 7 == 0 else i % 3) for i in range(60)]
    keyed = spark.createDataFrame(rows, "src long, dst long, key int").withColumn("slice", F.struct("key"))
    return rows, G.ranked(keyed, "slice", "src")


def test_ranks_by_two_columns(spark):
    rows, got = _order(spark)
    want = sorted(rows, key=lambda r: (r[2] is not None, r[2] or 0, r[0], r[1]))
    assert [(r["src"], r["dst"]) for r in got.orderBy("pos").collect()] == [r[:2] for r in want]
    assert [r["pos"] for r in got.orderBy("pos").collect()] == list(range(1, 61))


def test_slices_by_date_are_counted_side_by_side(spark, capsys):
    G.arrival_by(spark, "/root/testdata/sf0.001", "date").explain(True)
    plan = capsys.readouterr().out.split("== Physical Plan ==")[-1]
    singles = [x for x in plan.split("\n") if "SinglePartition" in x]
    windows = [x for x in plan.split("\n") if "Window [" in x and "sum(" in x]
    # of the sums over earlier slices, the one over dates alone is in one task
    assert len(singles) == 1 and len(windows) == 2


def test_orders_are_not_sent_to_the_driver(spark, capsys):
    # here orders are small; at 60 times sf0.1 their file still passes for it
    for e in (G.build(spark, "/root/testdata/sf0.001", "g_dense"), G.build(spark, "/root/testdata/sf0.001", "g_mid"), G.arrival_by(spark, "/root/testdata/sf0.001", "date")):
        e.select("src").explain()
        plan = capsys.readouterr().out
        assert "SortMergeJoin" in plan and not any("BroadcastHashJoin [l_orderkey" in x for x in plan.split("\n"))
