"""The Monte-Carlo baseline as DataFrame rounds: stored walks, their visit index, and rerouting after arc updates.

WALKS rows are (root, walk_id, path, stuck): a walk stops at a vertex with probability alpha, else goes to a random head;
one that cannot go on is stuck. All choices are hashes of (seed, epoch, root, walk, position), so a run can be repeated.
Heads are looked up by (vertex, number) in a table of numbered arcs, so a hub's list is never held in one row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from driftrank.engine import cut_lineage


def uniform(what: str, seed: int, *parts: str) -> Column:
    """A number in [0, 1) with 32 bits, from the md5 of the parts."""
    text = F.concat_ws(":", F.lit(f"{what}{seed}"), *(F.col(p).cast("string") for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / 2.0**32


def numbered(arcs: DataFrame) -> DataFrame:
    """(node, k, head): each vertex's heads in ascending order, numbered from 0."""
    order = Window.partitionBy("src").orderBy("dst")
    return arcs.select(F.col("src").alias("node"), (F.row_number().over(order) - 1).alias("k"), F.col("dst").alias("head"))


def _degrees(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("d"))


def grow(walks: DataFrame, arcs: DataFrame, alpha: float, seed: int, epoch: int = 0, cut: int = 8, max_len: int = 1000) -> DataFrame:
    """Walks (root, walk_id, path, fresh) gone on from their last vertex until they stop, as WALKS rows; those not ``fresh`` stay.

    Raises if a walk is longer than ``max_len``.
    """
    heads, degrees = cut_lineage(numbered(arcs), "heads"), cut_lineage(_degrees(arcs), "degrees")
    done, alive = walks.where("not fresh").select("root", "walk_id", "path", F.lit(False).alias("stuck")), walks.where("fresh").select("root", "walk_id", "path")
    for _ in range(0, max_len, cut):
        state = alive.withColumn("end", F.lit(0))  # 0: goes on, 1: stopped, 2: stuck
        for _ in range(cut):
            s = state.withColumns({"node": F.element_at("path", -1), "at": F.size("path")}).join(degrees, "node", "left")
            stop = uniform(f"s{epoch}.", seed, "root", "walk_id", "at") < alpha
            pick = F.floor(uniform(f"n{epoch}.", seed, "root", "walk_id", "at") * F.col("d"))
            end = F.when(F.col("end") > 0, F.col("end")).when(stop, 1).when(F.col("d").isNull(), 2).otherwise(0)
            s = s.withColumns({"end": end, "k": F.when(end == 0, pick).cast("int")}).drop("d", "at")
            s = s.join(heads, ["node", "k"], "left")
            state = s.select("root", "walk_id", F.when(F.col("head").isNull(), F.col("path")).otherwise(F.concat("path", F.array("head"))).alias("path"), "end")
        state = cut_lineage(state, "walks")
        done = done.union(state.where("end > 0").select("root", "walk_id", "path", (F.col("end") == 2).alias("stuck")))
        alive = state.where("end = 0").select("root", "walk_id", "path")
        if alive.isEmpty():
            return cut_lineage(done, "walks")
    raise RuntimeError(f"walks of over {max_len} vertices")


def generate(arcs: DataFrame, roots: DataFrame, r: int, alpha: float = 0.2, seed: int = 1) -> DataFrame:
    """``r`` walks from every root."""
    ids = F.explode(F.sequence(F.lit(1), F.lit(r))).alias("walk_id")
    start = roots.select(F.col("root").cast("long").alias("root"), ids).withColumns({"path": F.array("root"), "fresh": F.lit(True)})
    return grow(start, arcs, alpha, seed)


def index(walks: DataFrame) -> DataFrame:
    """(node, root, walk_id, pos) of every visit; pos counts from 0."""
    return walks.select("root", "walk_id", F.posexplode("path").alias("pos", "node")).select("node", "root", "walk_id", "pos")


def estimate(walks: DataFrame, r: int, how: str = "stop", alpha: float = 0.2) -> DataFrame:
    """(root, node, ppr): share of walks that stop at a vertex (stuck ones stop nowhere), or alpha times visits a walk."""
    if how == "stop":
        return walks.where("not stuck").groupBy("root", F.element_at("path", -1).alias("node")).agg((F.count("*") / r).alias("ppr"))
    return index(walks).groupBy("root", "node").agg((F.count("*") * alpha / r).alias("ppr"))


def storage(walks: DataFrame) -> DataFrame:
    """(root, vertices, bytes): 4 bytes a vertex of a path."""
    return walks.groupBy("root").agg(F.sum(F.size("path")).cast("long").alias("vertices"), (F.sum(F.size("path")) * 4).cast("long").alias("bytes"))


def _restarted(walks: DataFrame, cuts: DataFrame) -> DataFrame:
    """All walks, those in ``cuts`` (root, walk_id, pos, head, halt) cut after pos, with the head (if any), to go on unless halted."""
    j = walks.join(cuts, ["root", "walk_id"], "left")
    cut = F.slice("path", 1, F.col("pos") + 1)
    path = F.when(F.col("pos").isNull(), F.col("path")).when(F.col("halt"), cut).otherwise(F.concat(cut, F.array("head")))
    return j.select("root", "walk_id", path.alias("path"), F.col("pos").isNotNull().alias("cut"), F.when(F.col("pos").isNull(), F.col("stuck")).otherwise(F.col("halt")).alias("stuck"))


def _gone_on(walks: DataFrame, cuts: DataFrame, arcs: DataFrame, alpha: float, seed: int, epoch: int) -> DataFrame:
    moved = cut_lineage(_restarted(walks, cuts), "rerouted")
    fresh = moved.where("cut and not stuck").select("root", "walk_id", "path", F.lit(True).alias("fresh"))
    kept = moved.where("not cut or stuck").select("root", "walk_id", "path", "stuck")
    return kept.union(grow(fresh, arcs, alpha, seed, epoch))


def _first(cuts: DataFrame) -> DataFrame:
    """Of each walk, the earliest cut."""
    return cuts.groupBy("root", "walk_id").agg(F.min(F.struct("pos", "head", "halt")).alias("c")).select("root", "walk_id", "c.*")


def reroute_insert(walks: DataFrame, batch: DataFrame, arcs: DataFrame, alpha: float = 0.2, seed: int = 1, epoch: int = 1) -> DataFrame:
    """WALKS after the arcs of ``batch`` (src, dst) came in; ``arcs`` has them already.

    At each visit of a vertex with new heads that was followed by a step, the step goes to a new head with the share that
    the new heads have in the degree; the first such visit of a walk counts, and the walk goes on afresh. Walks that were
    stuck at a vertex that had no heads go on. Only walks that visit a changed vertex are read beyond the join.
    """
    new = numbered(batch).withColumnRenamed("k", "j")
    sizes = batch.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("k")).join(_degrees(arcs), "node")
    at = index(walks).join(sizes, "node").join(walks.select("root", "walk_id", F.size("path").alias("n"), "stuck"), ["root", "walk_id"])
    u = uniform(f"i{epoch}.", seed, "root", "walk_id", "pos")
    moves = ((F.col("pos") < F.col("n") - 1) | F.col("stuck")) & (u * F.col("d") < F.col("k"))
    hit = at.where(moves).withColumn("j", F.floor(u * F.col("d")).cast("int"))
    cuts = hit.join(new, ["node", "j"]).select("root", "walk_id", "pos", "head", F.lit(False).alias("halt"))
    return _gone_on(walks, _first(cuts), arcs, alpha, seed, epoch)


def reroute_delete(walks: DataFrame, batch: DataFrame, arcs: DataFrame, alpha: float = 0.2, seed: int = 1, epoch: int = 1) -> DataFrame:
    """WALKS after the arcs of ``batch`` went; ``arcs`` lacks them. A walk is cut before its first step over one of them,
    draws anew among the heads that are left (none: it is stuck there) and goes on afresh."""
    steps = index(walks)
    after = steps.select("root", "walk_id", (F.col("pos") - 1).alias("pos"), F.col("node").alias("to"))
    over = steps.join(after, ["root", "walk_id", "pos"]).join(batch.select(F.col("src").alias("node"), F.col("dst").alias("to")), ["node", "to"], "left_semi")
    drawn = over.join(_degrees(arcs), "node", "left").withColumn("k", F.floor(uniform(f"d{epoch}.", seed, "root", "walk_id", "pos") * F.col("d")).cast("int"))
    cuts = drawn.join(numbered(arcs), ["node", "k"], "left").select("root", "walk_id", "pos", "head", F.col("head").isNull().alias("halt"))
    return _gone_on(walks, _first(cuts), arcs, alpha, seed, epoch)
