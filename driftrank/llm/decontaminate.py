"""Benchmark decontamination: SimHash of item-sized windows, multi-index Hamming search, exact verification.

Texts are lower-cased, punctuation becomes white space. A window of as many words as an item has is compared by its
weighted five-word shingles. Only windows with enough shingles that occur in any item can reach the similarity, so only
those get a fingerprint. Fingerprints are cut into BLOCKS blocks; two within RADIUS differ by at most RADIUS // BLOCKS
bits in one of them, so looking up each block's neighbours finds all of them. Candidates are verified exactly.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from driftrank.llm import words as W

SHINGLE, RADIUS, BLOCKS = 5, 24, 8
ITEMS = 20_000  # items of one broadcast index; more are searched in several passes


def normal_words(texts: pa.Array) -> W.Words:
    low = pc.utf8_lower(pc.fill_null(texts, "").cast(pa.large_string()))
    return W.Words(pc.replace_substring_regex(low, r"[\pP\pS]+", " "))


def simhash(weights: Counter) -> int:
    """64-bit SimHash of weighted shingle hashes: each bit by the weighted vote of the shingles' bits."""
    h = np.array(list(weights), np.uint64)
    w = np.array(list(weights.values()), np.int64)
    bits = (h[:, None] >> np.arange(64, dtype=np.uint64)) & np.uint64(1)
    votes = (np.where(bits == 1, 1, -1) * w[:, None]).sum(axis=0)
    return int(((votes > 0).astype(np.uint64) << np.arange(64, dtype=np.uint64)).sum())


def similarity(a: Counter, b: Counter) -> float:
    """Weighted Jaccard: sum of the lesser weights over sum of the greater ones."""
    low = sum(min(n, b[g]) for g, n in a.items())
    return low / max(1, sum(a.values()) + sum(b.values()) - low)


def _near(bits: int, radius: int) -> np.ndarray:
    x = np.arange(1 << bits)
    near = np.array([bin(v).count("1") for v in range(1 << bits)])
    return x[near[x] <= radius]


class Index:
    """Items by window size, their shingles, and block tables for the Hamming search."""

    def __init__(self, ids: list, texts: list[str], similar: float):
        self.similar, self.items = similar, []
        w = normal_words(pa.array(texts, pa.large_string()))
        h = w.hashes(5)
        for i, s, e in zip(ids, w.starts[:-1], w.starts[1:], strict=True):
            if e > s:
                k = min(SHINGLE, int(e - s))
                g = W.mix(W.rolling(h[s:e], k) + np.uint64(k))
                bag = Counter(g.tolist())
                self.items.append((i, int(e - s), k, bag, simhash(bag)))
        self.sizes = sorted({n for _, n, _, _, _ in self.items})
        self.grams = {k: np.unique(np.array([x for t in self.items if t[2] == k for x in t[3]], np.uint64)) for k in {t[2] for t in self.items}}
        near = _near(64 // BLOCKS, RADIUS // BLOCKS)
        self.table: dict[tuple[int, int, int], list[int]] = {}
        for at, (_, n, _, _, f) in enumerate(self.items):
            for b in range(BLOCKS):
                own = (f >> (8 * b)) & 255
                for x in near.tolist():
                    self.table.setdefault((n, b, own ^ x), []).append(at)

    def search(self, n: int, bag: Counter) -> list[tuple[int, float]]:
        f = simhash(bag)
        found = {a for b in range(BLOCKS) for a in self.table.get((n, b, (f >> (8 * b)) & 255), ())}
        out = []
        for a in found:
            if bin(f ^ self.items[a][4]).count("1") <= RADIUS:
                s = similarity(bag, self.items[a][3])
                if s >= self.similar:
                    out.append((a, s))
        return out


def _scan(words: W.Words, index: Index) -> dict[tuple[int, int], tuple[float, int]]:
    """(row, item) -> (similarity, start) of its best window; ties: the first."""
    best: dict[tuple[int, int], tuple[float, int]] = {}
    if not words.n or not index.items:
        return best
    h, left, rows = words.hashes(5), words.left(), words.rows()
    for k, grams in index.grams.items():
        g = W.mix(W.rolling(h, k) + np.uint64(k))
        if not len(g):
            continue
        at = np.minimum(np.searchsorted(grams, g), len(grams) - 1)
        hit = (grams[at] == g) & (left[: len(g)] >= k)
        spots = np.flatnonzero(hit)
        if not len(spots):
            continue
        total = np.concatenate(([0], np.cumsum(hit)))
        for n in [n for n in index.sizes if min(n, SHINGLE) == k]:
            m = n - k + 1  # shingles in a window
            # starts from which a window can hold a hit; texts shorter than the item are one short window
            tries = np.unique((spots[:, None] - np.arange(m)).ravel()) if m > 1 else spots
            tries = tries[tries >= 0]
            size = np.minimum(m, left[tries] - k + 1)
            short = size < m
            least = np.ceil((m + size) * index.similar / (1 + index.similar) - 1e-9)  # overlap of bags of m and size shingles
            ok = (size > 0) & (~short | (tries == words.starts[rows[tries]])) & (total[np.minimum(tries + np.maximum(size, 0), len(g))] - total[np.minimum(tries, len(g))] >= least)
            for s, c in zip(tries[ok].tolist(), size[ok].tolist(), strict=True):
                for a, sim in index.search(n, Counter(g[s : s + c].tolist())):
                    key = (int(rows[s]), a)
                    if key not in best or sim > best[key][0]:
                        best[key] = (sim, s - int(words.starts[rows[s]]))
    return best


def find_leaks(frame: DataFrame, benchmark: DataFrame, similar: float = 0.8) -> DataFrame:
    """(doc_id, item_id, start_word, similarity): for each row and item that it holds, the best window.

    Empty or null texts hold nothing, empty or null items are never found; repeated rows repeat their finds. Items are
    searched in blocks of ITEMS, each broadcast once.
    """
    spark = frame.sparkSession
    kind = frame.schema["doc_id"].dataType.simpleString()
    item_kind = benchmark.schema["item_id"].dataType.simpleString()
    id_type = to_arrow_type(benchmark.schema["item_id"].dataType)
    items = benchmark.select("item_id", F.col("text").alias("t")).where("t is not null").distinct()
    passes = max(1, -(-items.count() // ITEMS))
    out = None
    for p in range(passes):
        own = items.where(F.pmod(F.xxhash64("item_id", "t"), F.lit(passes)) == p).orderBy("item_id", "t").toPandas()
        index = spark.sparkContext.broadcast(Index(own["item_id"].tolist(), own["t"].tolist(), similar))

        def run(batches, index=index):
            for b in W.slices(batches):
                best = _scan(normal_words(b.column(1)), index.value)
                if best:
                    keys = sorted(best)
                    yield pa.record_batch({"doc_id": b.column(0).take(pa.array([r for r, _ in keys])), "item_id": pa.array([index.value.items[a][0] for _, a in keys], id_type), "start_word": pa.array([best[k][1] for k in keys], pa.int64()), "similarity": pa.array([best[k][0] for k in keys], pa.float64())})

        found = frame.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, item_id {item_kind}, start_word long, similarity double")
        out = found if out is None else out.union(found)
    return out


def op2_decontaminate(spark, sf_dir) -> DataFrame:
    return find_leaks(W.docs(spark, sf_dir), W.docs(spark, sf_dir, "benchmark"))
