"""Graphs built from the given tables, and the basic relations over them. Vertex id = key * 8 + kind."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from driftrank.engine import cut_lineage

KINDS = {"path": 0, "order": 1, "part": 2, "customer": 3, "supplier": 4, "user": 5, "key": 6, "page": 7}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vid(key: str | Column, kind: str) -> Column:
    return (F.col(key) if isinstance(key, str) else key).cast("long") * 8 + KINDS[kind]


def ordered_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its orders. Two columns of a well packed orders file pass for small, so a join by sorting is asked for: no driver could hold them."""
    return table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))


def build(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Distinct (src, dst) of one graph; undirected ones have one orientation here, see undirect()."""
    t = lambda n: table(spark, sf_dir, n)
    if name == "g_sparse":
        e = t("lineitem").select(vid("l_orderkey", "order").alias("src"), vid("l_partkey", "part").alias("dst"))
    elif name in ("g_mid", "g_dense"):
        other = vid("l_partkey", "part") if name == "g_mid" else vid("l_suppkey", "supplier")
        e = ordered_items(spark, sf_dir).select(vid("o_custkey", "customer").alias("src"), other.alias("dst"))
    elif name == "g_ps":
        e = t("lineitem").select(vid("l_partkey", "part").alias("src"), vid("l_suppkey", "supplier").alias("dst"))
    elif name == "g_toggle":
        raw = toggles(spark, sf_dir)
        e = raw.groupBy("src", "dst").agg(F.count("*").alias("k")).where("k % 2 = 1").select("src", "dst")
    elif name == "g_next":
        k = F.get_json_object("props", "$.k").cast("long")
        w = Window.partitionBy("user_id").orderBy("ts", "event_id")
        e = t("events").select(k.alias("k"), F.lead(k).over(w).alias("n")).where("n is not null").select(vid("k", "key").alias("src"), vid("n", "key").alias("dst"))
    elif name == "g_web":
        links = t("pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("link")).distinct()
        key = F.conv(F.substring(F.md5("link"), 1, 12), 16, 10).cast("long")  # 48 bits of the link's hash: no ranking in one task
        e = links.select(vid("page_id", "page").alias("src"), vid(key, "path").alias("dst"))
    elif name == "g_geo":
        at = lambda key, kind: F.col(key).cast("long") * 8 + kind
        e = t("nation").select(at("n_nationkey", 1).alias("src"), at("n_regionkey", 0).alias("dst"))
        e = e.union(t("supplier").select(at("s_suppkey", 4), at("s_nationkey", 1))).union(t("customer").select(at("c_custkey", 3), at("c_nationkey", 1)))
    elif name == "g_knn":
        e = knn(t("embeddings"), 5)
    else:
        raise ValueError(f"no graph {name}")
    return e.where("src is not null and dst is not null").distinct()


def knn(vectors: DataFrame, k: int, block: int = 1024) -> DataFrame:
    """(src, dst): each vector's k nearest by cosine (9 digits; ties by id). All rows are the stated queries.

    Vectors are packed into blocks; a pair of blocks is one matrix product, which hands on k rows a query and no more.
    """
    near = "src long, dst long, s double"

    def pack(pdf):
        return pd.DataFrame({"b": [int(pdf["b"].iloc[0])], "ids": [pdf["vec_id"].tolist()], "body": [np.stack(pdf["embedding"]).astype("<f8").tobytes()]})

    def pairs(batches):
        for pdf in batches:
            for r in pdf.itertuples():
                q, v = (np.frombuffer(x).reshape(len(i), -1) for x, i in ((r.qbody, r.qids), (r.body, r.ids)))
                norm = lambda x: np.sqrt((x * x).sum(axis=1))
                s = np.round(q @ v.T / np.outer(norm(q), norm(v)), 9)
                qi, vi = np.asarray(r.qids), np.asarray(r.ids)
                s[qi[:, None] == vi[None]] = -np.inf
                order = np.stack([np.lexsort((vi, -row))[:k] for row in s])
                best = np.take_along_axis(s, order, 1)
                out = pd.DataFrame({"src": np.repeat(qi, order.shape[1]), "dst": vi[order].ravel(), "s": best.ravel()})
                yield out[np.isfinite(out["s"])]

    rows = vectors.where("vec_id is not null and embedding is not null")
    blocks = max(1, rows.count() // block)
    packed = rows.select("vec_id", "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("b")).groupBy("b").applyInPandas(pack, "b int, ids array<long>, body binary")
    packed = cut_lineage(packed, "blocks")
    left = packed.select(F.col("ids").alias("qids"), F.col("body").alias("qbody"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b"))
    best = Window.partitionBy("src").orderBy(F.col("s").desc(), "dst")
    found = left.join(packed, "b").mapInPandas(pairs, near)
    return found.withColumn("n", F.row_number().over(best)).where(F.col("n") <= k).select("src", "dst")


def toggles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(seq, src, dst, ts): every event toggles its (user, key) pair."""
    e = table(spark, sf_dir, "events")
    return pairs_of(e)


def pairs_of(events: DataFrame) -> DataFrame:
    """(seq, src, dst, ts) of events, batch or stream; events without a user or a key name no pair and are left out."""
    out = events.select(F.col("event_id").alias("seq"), vid("user_id", "user").alias("src"), vid(F.get_json_object("props", "$.k"), "key").alias("dst"), "ts")
    return out.where("src is not null and dst is not null")


def resolve_toggles(raw: DataFrame) -> DataFrame:
    """Edge events with op +1 / -1: the parity of a pair's earlier events; one exchange by pair."""
    w = Window.partitionBy("src", "dst").orderBy("ts", "seq")
    return raw.withColumn("op", F.when(F.row_number().over(w) % 2 == 1, 1).otherwise(-1)).select("seq", "src", "dst", "op", "ts")


def undirect(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").union(edges.select("dst", "src")).distinct()


def ends(edges: DataFrame) -> DataFrame:
    """(src) of all endpoints, with repeats: what roots are sampled from needs no distinct arcs."""
    return edges.select("src").union(edges.select("dst"))


def degrees(arcs: DataFrame) -> DataFrame:
    """(node, d_out, d_in) of all endpoints, by one exchange."""
    ends = arcs.select(F.col("src").alias("node"), F.lit(1).alias("o"), F.lit(0).alias("i")).union(arcs.select("dst", F.lit(0), F.lit(1)))
    return ends.groupBy("node").agg(F.sum("o").alias("d_out"), F.sum("i").alias("d_in"))


def stats(arcs: DataFrame) -> DataFrame:
    d = degrees(arcs)
    return d.agg(F.count("*").alias("n"), F.sum("d_out").alias("m"), F.round(F.avg("d_out"), 6).alias("avg_degree"))


def mean_degree(edges: DataFrame, undirected: bool) -> DataFrame:
    """avg_degree of stats(), of distinct ``edges`` or of both their ways; ways between vertices of different kinds are distinct as they are."""
    if undirected:
        kinds = edges.agg(F.collect_set(F.col("src") % 8).alias("a"), F.collect_set(F.col("dst") % 8).alias("b")).first()  # 8 kinds
        if not set(kinds["a"]) & set(kinds["b"]):
            n, m = ends(edges).distinct().count(), 2 * edges.count()
            return edges.sparkSession.range(1).select(F.round(F.lit(m / n if n else None).cast("double"), 6).alias("avg_degree"))
    return stats(undirect(edges) if undirected else edges).select("avg_degree")


def permutation(edges: DataFrame, seed: int = 1) -> DataFrame:
    """(src, dst, pos): a reproducible random arrival order, by md5 of the pair.

    Rows are ranked inside 65,536 slices of the hash, to which the rows of all earlier slices (one number each) are added.
    """
    return ranked(edges.select("src", "dst", F.md5(F.concat_ws(":", F.lit(str(seed)), "src", "dst")).alias("key")).withColumn("slice", F.substring("key", 1, 4)))


def arrival_by(spark: SparkSession, sf_dir: str, by: str) -> DataFrame:
    """(src, dst, pos) of g_dense by first order date, by the customer's degree (largest first) or by id; ties by id.

    Ranked inside slices by key and customer, of which a customer's edges are the largest. There are nearly as many slices as
    orders, so they are counted inside each key first.
    """
    if by == "random":
        return permutation(build(spark, sf_dir, "g_dense"))
    if by == "date":
        t = ordered_items(spark, sf_dir)
        e = t.groupBy(vid("o_custkey", "customer").alias("src"), vid("l_suppkey", "supplier").alias("dst")).agg(F.min("o_orderdate").alias("key"))
        e = e.where("src is not null and dst is not null")
    else:
        e = build(spark, sf_dir, "g_dense")
        e = e.withColumn("key", F.lit(0)) if by == "id" else e.join(e.groupBy("src").agg((-F.count("*")).alias("key")), "src")
    return ranked(e.withColumn("slice", F.struct("key")), "slice", "src")  # a struct equals its like, with a null in it too


def ranked(keyed: DataFrame, *slices: str) -> DataFrame:
    """(src, dst, pos) of rows (src, dst, key and the columns ``slices``, or slice) in the order of these, key, src, dst.

    The rows before a slice are those of lesser slices that agree with it in all columns but the last, which are added up
    side by side, and those before the slice without its last column.
    """
    slices = slices or ("slice",)
    names = [f"s{i}" for i in range(len(slices))]
    rows = keyed.select("src", "dst", "key", *(F.col(c).alias(n) for c, n in zip(slices, names, strict=True)))
    sizes = rows.groupBy(*names).agg(F.count("*").alias("n"))
    before = None
    for k in range(len(names), 0, -1):
        own = sizes if k == len(names) else sizes.groupBy(*names[:k]).agg(F.sum("n").alias("n"))
        lesser = Window.partitionBy(*names[: k - 1]).orderBy(names[k - 1]).rowsBetween(Window.unboundedPreceding, -1)
        own = own.select(*names[:k], F.coalesce(F.sum("n").over(lesser), F.lit(0)).alias(f"b{k}"))
        before = own if before is None else before.join(own, names[:k])
    ahead = sum((F.col(f"b{k}") for k in range(1, len(names) + 1)), F.lit(0))
    here = F.row_number().over(Window.partitionBy(*names).orderBy("key", "src", "dst"))
    return rows.withColumn("here", here).join(before, names).select("src", "dst", (F.col("here") + ahead).cast("long").alias("pos"))


def sample_roots(arcs: DataFrame, k: int, seed: int = 1) -> DataFrame:
    nodes = arcs.select(F.col("src").alias("root")).distinct()
    return nodes.orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), "root")), "root").limit(k)
