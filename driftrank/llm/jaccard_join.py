"""N-gram Jaccard join by T-occurrence search (DivideSkip), made for hot groups.

Rows with the same shingle set become one class. For a set of n shingles to reach the wanted overlap T with another,
it must meet it in one of its n-T+1 rarest shingles, so those are the short lists that are spread over the cluster;
all others are the long lists that are only probed. Each list is named by its least member (its leader), so the many
lists of one group of copies fall into few blocks; lists stream by in order, none is held. A block is searched by
DivideSkip: short inverted lists are heap-merged, long ones probed by binary search. A block over ``CHUNK`` members is
searched in chunks that all hold its leader; only members that did not come to be linked with the leader there meet the
other chunks. A search returns a spanning forest of links, never all pairs; distributed components join them.
"""

from __future__ import annotations

import heapq
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.llm import words as W
from driftrank.llm.components import components

CELLS = 1 << 21
CHUNK = 512
BITS = 1 << 26  # of the filter of searched ids, whatever the input; ids that it lets through in error are joined away


def overlap_needed(n: int, m: int, percent: int) -> int:
    """Least intersection i with 100*i >= percent*(n+m-i)."""
    return -(-percent * (n + m) // (100 + percent))


def prefix_length(n: int, percent: int) -> int:
    """Short lists of a set of n: n - T + 1 for the least T that any partner allows (percent of n)."""
    return n - max(1, -(-percent * n // 100)) + 1


def _cells(h: np.ndarray) -> np.ndarray:
    return (W.mix(h) >> np.uint64(43)).astype(np.int64)


def word_frequencies(frame: DataFrame) -> np.ndarray:
    """Word counts over all rows in a sketch of CELLS counters; used for an order of lists only, so it loses nothing."""

    def fill(mine, b):
        w = W.Words(b.column(b.schema.get_field_index("text")), lower=True)
        if w.n:
            h = np.fromiter((xxhash.xxh3_64_intdigest(v, 7) for v in w.vocab), np.uint64, len(w.vocab))
            np.add.at(mine, _cells(h), np.bincount(w.codes, minlength=len(h)))

    return W.summed_sketch(frame.select("text"), CELLS, fill)


def set_rows(frame: DataFrame, k: int, percent: int, freq) -> DataFrame:
    """(doc_id, n_shingles, d1, d2, short): each row's set size, 128-bit digest and short lists, rarest shingles first.

    Rarity of a shingle: the least count among its words.
    """

    def run(words, b):
        f = np.minimum(freq.value[_cells(words.hashes(7))], (1 << 20) - 1) if words.n else np.zeros(0, np.int64)
        n, d, short = [], [], []
        for u, low in W.shingle_sets(words, k, f):
            n.append(len(u))
            d.append(xxhash.xxh3_128_digest(u.tobytes()))
            if len(u):
                p = prefix_length(len(u), percent)
                # shingles come in order of hash, so a stable order by count breaks ties alike in all rows
                u = u[np.argsort(low, kind="stable")[:p]] if p < len(u) else u
            short.append(u)
        d = np.frombuffer(b"".join(d), np.int64).reshape(-1, 2)
        cut = np.concatenate(([0], np.cumsum([len(x) for x in short]))).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(cut), pa.array(np.concatenate(short).view(np.int64)))
        return pa.record_batch({"doc_id": b.column(0).cast(pa.int64()), "n_shingles": pa.array(n, pa.int64()), "d1": pa.array(d[:, 0].copy()), "d2": pa.array(d[:, 1].copy()), "short": lists})

    return frame.select("doc_id", "text").mapInArrow(W.arrow(run, lower=True), "doc_id long, n_shingles long, d1 long, d2 long, short array<long>")


def block_members(posts: DataFrame, percent: int) -> DataFrame:
    """(leader, doc_id), distinct: postings (g, doc_id, n) whose list has a second member of a size that can link.

    A list is cut by size class, so that its members that can link meet in one of two neighbouring classes. Lists come
    sorted by member; the first of a list and class is its leader, so only the leaders of one list are held.
    """
    # classes [r^c, r^(c+1)) with r = 100 / percent: sizes that can link lie in one class or in neighbours
    step = np.log(100.0 / percent)

    def run(batches):
        lead = np.zeros((0, 4), np.int64)  # g, class, leader, whether it has a second member, of the list at hand
        for b in batches:
            if not b.num_rows:
                continue
            g, ids, n = (b.column(k).to_numpy() for k in range(3))
            c = np.floor(np.log(n) / step + 1e-9).astype(np.int64)
            rows = np.stack((np.tile(g, 2), np.concatenate((c, c + 1)), np.tile(ids, 2), np.full(2 * len(g), -1)), 1)
            rows = np.concatenate((lead, rows))
            rows = rows[np.lexsort((-rows[:, 3], rows[:, 2], rows[:, 1], rows[:, 0]))]
            new = np.ones(len(rows), bool)
            new[1:] = (rows[1:, :2] != rows[:-1, :2]).any(axis=1)
            begin = np.flatnonzero(new)
            size = np.diff(np.append(begin, len(rows)))
            first = np.repeat(rows[begin, 2], size)
            other = np.add.reduceat((rows[:, 2] != first).astype(np.int64), begin) > 0
            told = rows[begin, 3] == 1
            keep = np.repeat(other, size) & ((rows[:, 2] != first) | np.repeat(~told, size))
            out = np.unique(np.stack((first[keep], rows[keep, 2]), 1), axis=0)
            yield pa.record_batch({"leader": pa.array(out[:, 0].copy()), "doc_id": pa.array(out[:, 1].copy())})
            last = rows[begin, 0] == g[-1]
            lead = np.stack((rows[begin, 0], rows[begin, 1], rows[begin, 2], (other | told).astype(np.int64)), 1)[last]

    dealt = posts.repartition("g").sortWithinPartitions("g", "doc_id")
    return dealt.select("g", "doc_id", F.col("n").cast("double")).mapInArrow(run, "leader long, doc_id long").distinct()


def id_filter(ids: DataFrame) -> np.ndarray:
    """A bitmap of BITS bits of hashed ids (one long column): every id of the column is in it, some others too."""

    def part(batches):
        bits = np.zeros(BITS, bool)
        for b in batches:
            bits[_places(b.column(0).to_numpy())] = True
        yield pa.record_batch({"body": pa.array([zlib.compress(np.packbits(bits).tobytes(), 1)], pa.binary())})

    out = np.zeros(BITS // 8, np.uint8)
    for r in ids.mapInArrow(part, "body binary").toLocalIterator():  # one row a task, at most BITS / 8 bytes each
        out |= np.frombuffer(zlib.decompress(bytes(r["body"])), np.uint8)
    return out


def _places(ids: np.ndarray) -> np.ndarray:
    return (W.mix(ids.astype(np.int64).view(np.uint64)) & np.uint64(BITS - 1)).astype(np.int64)


def texts_of(base: DataFrame, bits) -> DataFrame:
    """Rows of (doc_id, text) whose id may be in the filter: what is left out needs no exchange."""

    def run(batches):
        for b in batches:
            at = _places(pc.fill_null(b.column(0), 0).to_numpy())
            yield b.filter(pa.array(((bits.value[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1).astype(bool)))

    return base.where("doc_id is not null").mapInArrow(run, "doc_id long, text string")


class Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        if x != y:
            self.up[max(x, y)] = min(x, y)
        return x != y


def divide_skip(sets: list[np.ndarray], percent: int, side: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that span the components of ``sets`` under 100*|x&y| >= percent*|x|y|, found by T-occurrence search.

    ``side``: with two sides, only pairs across them are looked at. Pairs already connected are skipped.
    """
    m = len(sets)
    sizes = np.array([len(s) for s in sets], np.int64)
    order = np.argsort(sizes, kind="stable")
    owner = np.repeat(np.arange(m), sizes[order])
    every = np.concatenate([sets[i] for i in order]) if m else np.zeros(0, np.uint64)
    by = np.argsort(every, kind="stable")
    grams, first = np.unique(every[by], return_index=True)
    ends = np.append(first[1:], len(every))
    lists = owner[by]  # ascending within each gram, as owners are
    forest, links, n = Forest(m), [], sizes[order]
    for x in range(m):
        mine = sets[order[x]]
        if not len(mine):
            continue
        top = int(np.searchsorted(n, 100 * n[x] // percent, side="right"))  # partners: sizes from mine to mine*100/percent
        if top <= x + 1:
            continue
        at = np.searchsorted(grams, mine)
        los, his = first[at], ends[at]
        length = his - los
        rank = np.argsort(length, kind="stable")
        need = overlap_needed(int(n[x]), int(n[x]), percent)
        long_n = min(need - 1, len(mine))
        short, long = rank[: len(mine) - long_n], rank[len(mine) - long_n :]
        runs = [r[np.searchsorted(r, x, side="right") : np.searchsorted(r, top)] for r in (lists[los[j] : his[j]] for j in short)]
        runs = [r for r in runs if len(r)]
        if not runs:
            continue
        if sum(map(len, runs)) <= 4096:
            merged = np.fromiter(heapq.merge(*(r.tolist() for r in runs)), np.int64)
        else:
            merged = np.sort(np.concatenate(runs), kind="stable")
        new = np.flatnonzero(np.diff(merged, prepend=-1))
        cand, hits = merged[new], np.diff(np.append(new, len(merged)))
        here = forest.find(x)
        keep = np.fromiter((forest.find(int(c)) != here for c in cand), bool, len(cand)) if len(cand) else np.zeros(0, bool)
        if side is not None:
            keep &= side[order[cand]] != side[order[x]]
        cand, hits = cand[keep], hits[keep]
        wanted = -(-percent * (n[x] + n[cand]) // (100 + percent))
        for done, j in enumerate(long):
            if not len(cand):
                break
            r = lists[los[j] : his[j]]
            p = np.searchsorted(r, cand)
            hits = hits + (r[np.minimum(p, len(r) - 1)] == cand)
            if done % 8 == 7:
                ok = hits + (len(long) - done - 1) >= wanted
                if not ok.all():
                    cand, hits, wanted = cand[ok], hits[ok], wanted[ok]
        for c in cand[hits >= wanted].tolist():
            if forest.join(x, c):
                links.append((int(order[x]), int(order[c])))
    return links


def _members_search(blocks: DataFrame, k: int, percent: int) -> DataFrame:
    """(leader, chunk, a, b): spanning links of each group (leader, chunk, part) of blocks (.., side, doc_id, text).

    A group whose rows have two sides is searched across them alone. Rows left without a link to their leader come
    back as (a, a), of whole groups (``side`` null) over CHUNK members only.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        sets = [u for u, _ in W.shingle_sets(W.Words(pa.array(pdf["text"], pa.large_string()), lower=True), k)]
        ids, across = pdf["doc_id"].to_numpy(), pdf["side"].notna().all()
        links = divide_skip(sets, percent, pdf["side"].to_numpy() if across else None)
        a, b = [ids[x] for x, _ in links], [ids[y] for _, y in links]
        if not across and pdf["many"].iloc[0]:
            forest, leader = Forest(len(ids)), pdf["leader"].iloc[0]
            for x, y in links:
                forest.join(x, y)
            tops = {forest.find(x) for x in np.flatnonzero(ids == leader).tolist()}
            apart = [ids[x] for x in range(len(ids)) if forest.find(x) not in tops]
            a, b = a + apart, b + apart
        return pd.DataFrame({"leader": pdf["leader"].iloc[0], "chunk": pdf["chunk"].iloc[0], "a": a, "b": b}).astype("int64")

    return blocks.groupBy("leader", "chunk", "part").applyInPandas(run, "leader long, chunk long, a long, b long")


def search_blocks(members: DataFrame, texts: DataFrame, k: int, percent: int) -> DataFrame:
    """(a, b): links that span the components of each block; members has (leader, doc_id), texts (doc_id, text)."""
    sizes = members.groupBy("leader").agg(F.count("*").alias("m"))
    chunks = F.ceil(F.col("m") / CHUNK).cast("int")
    placed = members.join(sizes, "leader").withColumn("c", chunks).withColumn("chunk", F.pmod(F.xxhash64("doc_id"), F.col("c")).cast("int"))
    # the leader goes into every chunk of its block
    own = F.when(F.col("doc_id") == F.col("leader"), F.sequence(F.lit(0), F.col("c") - 1)).otherwise(F.array("chunk"))
    none = F.lit(None).cast("int")
    first = placed.select("doc_id", "leader", F.explode(own).alias("chunk"), F.lit(0).alias("part"), none.alias("side"), (F.col("c") > 1).alias("many"))
    found = W.written(_members_search(with_text(first, texts), k, percent), "links")
    # members of large blocks that are apart from their leader: each meets the other chunks, all of their members
    apart = found.where("a = b").select("leader", F.col("a").alias("doc_id"), F.col("chunk").cast("int").alias("from")).distinct()
    lots = apart.groupBy("leader").agg(F.ceil(F.count("*") / CHUNK).cast("int").alias("lots"))
    large = placed.where("c > 1").join(lots, "leader")
    tail = apart.join(large.select("leader", "c", "lots").distinct(), "leader").withColumn("part", F.pmod(F.xxhash64("doc_id"), F.col("lots")).cast("int"))
    tail = tail.withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("c") - 1))).where("chunk <> from")
    whole = large.select("doc_id", "leader", "chunk", F.explode(F.sequence(F.lit(0), F.col("lots") - 1)).alias("part"), F.lit(0).alias("side"), F.lit(True).alias("many"))
    second = whole.unionByName(tail.select("doc_id", "leader", "chunk", "part", F.lit(1).alias("side"), F.lit(True).alias("many")))
    return found.where("a <> b").select("a", "b").union(_members_search(with_text(second, texts), k, percent).where("a <> b").select("a", "b"))


def with_text(places: DataFrame, texts: DataFrame) -> DataFrame:
    """A text travels once to all the places of its id; an id that occurs with several texts is searched with each."""
    names = [c for c in places.columns if c != "doc_id"]
    spread = places.groupBy("doc_id").agg(F.collect_list(F.struct(*names)).alias("at"))
    return texts.join(spread, "doc_id").select("doc_id", "text", F.explode("at").alias("s")).select("doc_id", "text", "s.*")


def jaccard_classes(frame: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id) for each row of ``frame`` (doc_id, text).

    A link: 100 * intersection >= percent * union of distinct k-word shingles (A-Z lower-cased; with fewer words, the
    whole sequence as one). component_id is the least doc_id reachable, the row's own included. Null or empty texts
    have no shingles and no links. Rows whose doc_id is null never link and get a null component. Repeated rows each
    get a row. Other columns are ignored. An empty frame gives an empty result.
    """
    spark = frame.sparkSession
    base = frame.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    freq = spark.sparkContext.broadcast(word_frequencies(base))
    sets = W.written(set_rows(base, k, percent, freq), "sets")
    marks = sets.drop("short")
    # rows of one class have one set, so the lists of any of them are those of all
    classes = sets.where("n_shingles > 0 and doc_id is not null").groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("short").alias("short"))
    classes = W.written(classes, "classes")
    posts = classes.select(F.explode("short").alias("g"), F.col("rep").alias("doc_id"), "n")
    members = W.written(block_members(posts, percent), "members")
    bits = spark.sparkContext.broadcast(id_filter(members.select("doc_id")))
    links = W.written(search_blocks(members, texts_of(base, bits), k, percent), "links")
    found = W.written(components(links), "components")
    W.dropped(members, links)
    mapped = marks.join(classes.select("d1", "d2", "rep"), ["d1", "d2"], "left")
    linked = mapped.join(found.withColumnRenamed("node", "rep"), "rep", "left")
    return linked.select("doc_id", "n_shingles", F.when(F.col("n_shingles") > 0, F.coalesce("component", "rep")).otherwise(F.col("doc_id")).alias("component_id"))


def similar_pairs(frame: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, component_id) of rows that share a component with another row: the join's class membership."""
    c = jaccard_classes(frame, k, percent)
    many = c.groupBy("component_id").agg(F.count("*").alias("rows")).where("rows > 1")
    return c.join(many, "component_id").select("doc_id", "component_id")


def op7_jaccard_join(spark, sf_dir) -> DataFrame:
    return jaccard_classes(W.docs(spark, sf_dir), k=3, percent=90)
