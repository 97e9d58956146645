"""Vectorised word handling shared by the text operators.

A word is ``[^\\x20\\x09-\\x0D]+``; Arrow's ASCII white-space split cuts at exactly these six bytes.
Everything here works on one bounded slice of a record batch, so memory does not follow the input.
"""

from __future__ import annotations

import ctypes
import gc
import os
import re
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 4 << 20
NO_ID = -(1 << 63)
_LOWER = {c: c + 32 for c in range(65, 91)}
_ODD = 0x9E3779B97F4A7C15


def mix(x: np.ndarray) -> np.ndarray:
    """Finalising bit mixer over unsigned 64-bit values."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None)  # not every C library has it


def trim() -> None:
    """Give freed memory back: a worker that waits, or begins another stage, else keeps what its largest slice took."""
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(ctypes.c_size_t(0))


def slices(batches: Iterator[pa.RecordBatch], text: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that each holds about ``limit`` bytes of text (one row at least)."""
    for b in batches:
        if not b.num_rows:
            continue
        col = b.column(b.schema.get_field_index(text))
        ends = np.cumsum(pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 64)
        at, base = 0, 0
        while at < b.num_rows:
            to = max(at + 1, int(np.searchsorted(ends, base + limit, side="right")))
            yield b.slice(at, to - at)
            at, base = to, int(ends[to - 1])
        del b, col
        trim()


def strings(col: pa.Array) -> list[str]:
    """The column as Python strings; to_pylist() takes some ten times as long."""
    return col.to_numpy(zero_copy_only=False).tolist()


class Words:
    """The words of one slice: ``vocab`` (distinct), ``codes`` (one per word) and ``starts`` (row offsets)."""

    def __init__(self, texts: pa.Array, lower: bool = False):
        texts = pc.fill_null(pa.array(texts) if not isinstance(texts, pa.Array) else texts, "").cast(pa.large_string())
        lists = pc.ascii_split_whitespace(texts)
        flat, offs = lists.flatten(), lists.offsets.to_numpy()
        offs = offs - offs[0]
        full = pc.greater(pc.binary_length(flat), 0).to_numpy(zero_copy_only=False)
        if not full.all():
            offs = np.concatenate(([0], np.cumsum(full)))[offs]
            flat = flat.filter(pa.array(full))
        coded = pc.dictionary_encode(flat)
        self.vocab: list[str] = strings(coded.dictionary)
        self.codes = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
        if lower:  # A-Z alone, and on the distinct words only
            again = pc.dictionary_encode(pa.array([w.lower() if w.isascii() else w.translate(_LOWER) for w in self.vocab], pa.large_string()))
            self.vocab = strings(again.dictionary)
            self.codes = again.indices.to_numpy(zero_copy_only=False).astype(np.int64)[self.codes]
        self.starts = offs.astype(np.int64)
        self.n = len(self.codes)
        self.hashed: dict[int, np.ndarray] = {}

    def rows(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.starts) - 1), np.diff(self.starts))

    def left(self) -> np.ndarray:
        """Per word: how many words of its row there are from it on."""
        return np.repeat(self.starts[1:], np.diff(self.starts)) - np.arange(self.n)

    def hashes(self, seed: int = 0) -> np.ndarray:
        if seed not in self.hashed:
            self.hashed[seed] = np.fromiter((xxhash.xxh3_64_intdigest(w, seed) for w in self.vocab), np.uint64, len(self.vocab))
        h = self.hashed[seed]
        return h[self.codes] if len(h) else np.zeros(0, np.uint64)


def rolling(h: np.ndarray, n: int, base: int = _ODD) -> np.ndarray:
    """Order-sensitive hash of every run of n values, by doubling; length len(h)-n+1 (or 0)."""
    if len(h) < n:
        return np.zeros(0, np.uint64)
    cur, size, acc, have, power = h, 1, None, 0, base
    while True:
        if n & size:
            if acc is None:
                acc, have = cur, size
            else:
                m = len(cur) - have
                acc = acc[:m] * np.uint64(power) + cur[have : have + m]
                have += size
        if size * 2 > n:
            return acc[: len(h) - n + 1]
        m = len(cur) - size
        cur = cur[:m] * np.uint64(power) + cur[size : size + m]
        size, power = size * 2, power * power & 0xFFFFFFFFFFFFFFFF


def sliding(a: np.ndarray, w: int, pick=np.minimum) -> np.ndarray:
    """Minimum (or maximum) of every run of w values."""
    if len(a) < w:
        return a[:0]
    cur, size = a, 1
    while size * 2 <= w:
        cur = pick(cur[: len(cur) - size], cur[size:])
        size *= 2
    n = len(a) - w + 1
    return pick(cur[:n], cur[w - size : w - size + n])


def shingle_sets(words: Words, k: int, extra: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray | None]]:
    """Per row: its distinct k-word shingle hashes, ascending; with fewer words, the whole sequence as one.

    ``extra`` has a value per word; the second item then is the smallest of each shingle's words.
    """
    h = words.hashes(7)
    g = mix(rolling(h, k))
    low = sliding(extra, k) if extra is not None else None
    for s, e in zip(words.starts[:-1].tolist(), words.starts[1:].tolist(), strict=True):
        if e - s >= k:
            u, at = np.unique(g[s : e - k + 1], return_index=True)
            yield u, low[s : e - k + 1][at] if low is not None else None
        elif e > s:
            u = mix(rolling(h[s:e], e - s) + np.uint64(e - s))
            yield u, np.array([extra[s:e].min()]) if extra is not None else None
        else:
            yield np.zeros(0, np.uint64), np.zeros(0, np.int64)


def docs(spark: SparkSession, sf_dir: str, table: str = "documents") -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir. A local master, as in tests, may do without one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not found.isDefined() and not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
        root = found.get() if found.isDefined() else "/tmp/checkpoints"
    return root.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write ``df`` as Parquet into the shared folder and read it back."""
    path = f"{shared(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dropped(*tables: DataFrame) -> None:
    """Delete tables that written() made, once nothing will read them again, and shuffles that are done with."""
    for t in tables:
        for f in {f.rsplit("/", 1)[0] for f in t.inputFiles()}:
            path = t.sparkSession._jvm.org.apache.hadoop.fs.Path(f)
            path.getFileSystem(t.sparkSession._jsc.hadoopConfiguration()).delete(path, True)
    if tables:
        freed(tables[0].sparkSession)


def freed(spark: SparkSession) -> None:
    """Let the driver find shuffles that are done with: frames lie in cycles, so Python has to let go of them first."""
    gc.collect()
    spark._jvm.System.gc()


def runs(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """begin[0] .. begin[0] + size[0] - 1, then the same of each following pair."""
    total = int(size.sum())
    step = np.ones(total, np.int64)
    full = np.flatnonzero(size)
    if not total:
        return step
    b, n = begin[full], size[full]
    at = np.cumsum(n)[:-1]
    step[0] = b[0]
    step[at] = b[1:] - b[:-1] - n[:-1] + 1
    return np.cumsum(step)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def keyed(frame: DataFrame) -> DataFrame:
    """doc_id, text and a row key (dk, th) that is never null: repeated rows share it, as they share every result."""
    return frame.select(
        "doc_id", "text", F.coalesce("doc_id", F.lit(NO_ID)).cast("long").alias("dk"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("th")
    )


def arrow(fn: Callable[[Words, pa.RecordBatch], pa.RecordBatch | None], lower: bool = False):
    """mapInArrow body: ``fn`` for each bounded slice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            out = fn(Words(b.column(b.schema.get_field_index("text")), lower), b)
            if out is not None:
                yield out

    return run


def summed_sketch(frame: DataFrame, cells: int, fill: Callable[[np.ndarray, pa.RecordBatch], None], text: str = "text") -> np.ndarray:
    """Counters of a fixed width over all rows: each partition fills its own, slabs are added up, the driver gets ``cells`` numbers.

    ``fill(counters, slice)`` adds to an int64 array. The size is ``cells`` whatever the input.
    """
    import zlib

    slab = min(cells, 1 << 16)

    def part(batches):
        mine = np.zeros(cells, np.int64)
        for b in slices(batches, text):
            fill(mine, b)
        at = [k for k in range(0, cells, slab) if mine[k : k + slab].any()]
        yield pa.record_batch({"slab": pa.array(at, pa.int64()), "body": pa.array([zlib.compress(mine[k : k + slab].tobytes(), 1) for k in at], pa.binary())})

    def merge(pdf):
        import pandas as pd

        total = np.zeros(min(slab, cells), np.int64)
        for body in pdf["body"]:
            x = np.frombuffer(zlib.decompress(body), np.int64)
            total[: len(x)] += x
        return pd.DataFrame({"slab": [int(pdf["slab"].iloc[0])], "body": [zlib.compress(total.tobytes(), 1)]})

    schema = "slab long, body binary"
    out = np.zeros(cells, np.int64)
    for r in frame.mapInArrow(part, schema).groupBy("slab").applyInPandas(merge, schema).toLocalIterator():
        x = np.frombuffer(zlib.decompress(bytes(r["body"])), np.int64)
        out[r["slab"] : r["slab"] + slab] = x[: min(slab, cells - r["slab"])]
    return out


def tokenizer_path(name: str, path: str | None = None) -> str:
    """A vocabulary file: ``path`` if given, else the installed public one."""
    import public_tokenizers

    return path or os.fspath(public_tokenizers.path(name))
