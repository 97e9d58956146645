"""Edge streams: a file source of toggles, windowed rates, and maintenance by micro-batch with versioned state."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from driftrank import engine, schemas
from driftrank.operators import push, repair
from driftrank.sources import graph as G


BLOCK_BITS = 9  # 64 vertices of one kind, whose edges are one state


def read_events(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schemas.EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def rates(events: DataFrame, late: str = "10 minutes", width: str = "1 hour") -> DataFrame:
    """Toggles per hour; events later than the watermark are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width)).agg(F.count("*").alias("toggles")).select(F.col("window.start").alias("start"), "toggles")


def resolve_stream(pairs: DataFrame, out: str, checkpoint: str) -> None:
    """Append (seq, src, dst, op) of a stream of toggles (seq, src, dst, ts) to Parquet in ``out``, until what is there has been read.

    The state of a pair is whether its edge is there, kept by the stream's own store, so a restart goes on from it. Pairs are
    kept by blocks of vertices, as the edges that are there, so that a call settles a block's toggles as arrays. Toggles of
    a pair count in the order of ts and seq inside a micro-batch. One block's
    toggles of a micro-batch are held at once: ``files_per_batch`` of read_events() bounds them.
    """

    def flip(key, parts, state):
        rows = pd.concat(list(parts), ignore_index=True).sort_values(["src", "dst", "ts", "seq"], ignore_index=True)
        held = np.frombuffer(state.get[0] if state.exists else b"", "<i8").reshape(-1, 2)
        by = rows.groupby(["src", "dst"])
        named = pd.MultiIndex.from_frame(rows[["src", "dst"]])
        there = pd.MultiIndex.from_arrays([held[:, 0], held[:, 1]])
        op = np.where((by.cumcount().to_numpy() + named.isin(there)) % 2 == 0, 1, -1).astype("int32")
        last = (by.cumcount(ascending=False) == 0).to_numpy() & (op == 1)
        now = np.concatenate((held[~there.isin(named)], rows.loc[last, ["src", "dst"]].to_numpy(np.int64)))
        state.update((now.astype("<i8").tobytes(),))
        yield pd.DataFrame({"seq": rows["seq"], "src": rows["src"], "dst": rows["dst"], "op": op})

    keyed = pairs.withColumn("block", F.shiftright("src", BLOCK_BITS)).groupBy("block").applyInPandasWithState(flip, "seq long, src long, dst long, op int", "edges binary", "append", "NoTimeout")
    keyed.writeStream.format("parquet").outputMode("append").option("path", out).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


class Maintained:
    """Keeps push states fresh over batches of toggles of undirected edges; use ``update`` in foreachBatch.

    An edge has one orientation, the lesser end first, whichever way a batch names it; pairs with a null end are left out,
    and a loop is one arc. Edges and state of the last batches are versions in ``folder``, valid once their mark is there:
    a new object over the same folder goes on after the last of them, and a batch that it covers is passed over.
    """

    KEEP = 2

    def __init__(self, spark: SparkSession, edges: DataFrame, roots: DataFrame, folder: str, alpha: float = 0.2, rmax: float = 1e-4):
        self.spark, self.folder, self.alpha, self.rmax = spark, folder.rstrip("/"), alpha, rmax
        hadoop = spark._jvm.org.apache.hadoop.fs
        self.path = hadoop.Path
        self.fs = hadoop.Path(self.folder).getFileSystem(spark._jsc.hadoopConfiguration())
        done = self.versions()
        if done:
            self.open(done[-1])
        else:
            first = canonical(edges)
            self.save(-1, first, push.forward(G.undirect(first), push.start_state(roots), alpha, rmax))

    def versions(self) -> list[int]:
        """Numbers of the versions that were written to their end."""
        marks = self.fs.globStatus(self.path(f"{self.folder}/v*/done")) or []
        return sorted(int(m.getPath().getParent().getName()[1:]) for m in marks)

    def open(self, version: int) -> None:
        at = f"{self.folder}/v{version}"
        self.last, self.edges = version, self.spark.read.schema(schemas.EDGES).parquet(f"{at}/edges")
        self.state = self.spark.read.schema(schemas.STATE).parquet(f"{at}/state")

    def save(self, version: int, edges: DataFrame, state: DataFrame) -> None:
        at = f"{self.folder}/v{version}"
        edges.select("src", "dst").write.mode("overwrite").parquet(f"{at}/edges")
        state.select("root", "node", "est", "res").write.mode("overwrite").parquet(f"{at}/state")
        self.fs.create(self.path(f"{at}/done"), True).close()
        self.open(version)
        for old in self.versions()[: -self.KEEP]:
            self.fs.delete(self.path(f"{self.folder}/v{old}"), True)

    def update(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        odd = oriented(batch).groupBy("src", "dst").agg(F.count("*").alias("k")).where("k % 2 = 1").select("src", "dst")
        here = self.edges.withColumn("here", F.lit(1))
        odd = engine.cut_lineage(odd.join(here, ["src", "dst"], "left").select("src", "dst", F.when(F.col("here") == 1, -1).otherwise(1).alias("op")), "batch")
        arcs = odd.union(odd.select("dst", "src", "op")).distinct()
        state = repair.lazy_forward(self.state, arcs, G.degrees(G.undirect(self.edges)), self.alpha)
        kept = engine.cut_lineage(self.edges.join(odd.where("op = -1"), ["src", "dst"], "left_anti").union(odd.where("op = 1").select("src", "dst")), "edges")
        self.save(batch_id, kept, push.forward(G.undirect(kept), engine.cut_lineage(state), self.alpha, self.rmax))

    def defect(self) -> float:
        """The greatest absolute defect of the state's identity; 0 up to rounding if the state fits the edges."""
        worst = repair.forward_defect(G.undirect(self.edges), self.state, self.alpha).agg(F.max(F.abs("defect"))).first()[0]
        return worst or 0.0


def oriented(pairs: DataFrame) -> DataFrame:
    """Pairs with the lesser end first, without those that have a null end."""
    return pairs.where("src is not null and dst is not null").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))


def canonical(edges: DataFrame) -> DataFrame:
    return oriented(edges).distinct()


def maintain_stream(spark: SparkSession, events: DataFrame, keeper: Maintained, checkpoint: str) -> None:
    """Run a stream of EVENTS rows through ``keeper`` until what is there has been read; a second call goes on where it was left."""
    query = G.pairs_of(events).writeStream.foreachBatch(lambda df, k: keeper.update(df, k)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
