"""Removal of repeated word windows behind a count-min prefilter.

A window of 35 words that repeats carries its least 8-word gram along, so that gram repeats as well. Each partition
counts its selected grams in a sketch of fixed width; merged, the counters never lie under a window's true count.
A second pass groups exactly, by 96 bits of hash under the 64 bits of their least gram, only the windows whose gram is
estimated to repeat. Neighbouring windows with one least gram travel as one row, dealt and sorted by that gram, and are
grouped as they stream by, so a task holds one batch and one gram's distinct windows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.llm import words as W

WINDOW, GRAM = 35, 8
WIDTH = 1 << 27  # counters of each of the sketch's two rows, whatever the input
SLAB = 1 << 20
_HASH = np.dtype([("h1", "<u8"), ("h2", "<u4")])
_ENTRY = np.dtype([("g", "<i8"), ("h1", "<u8"), ("h2", "<u4"), ("known", "?"), ("dk", "<i8"), ("th", "<i8"), ("pos", "<i4")])
SPOTS = "dk long, th long, pos int, n int"


def _grams(words: W.Words, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Gram hashes, the least gram of each window start, and which window starts are inside one row."""
    g = W.mix(W.rolling(words.hashes(11), gram))
    low = W.sliding(g, window - gram + 1)
    return g, low, words.left()[: len(low)] >= window


def _rows(g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return (g & np.uint64(WIDTH - 1)).astype(np.int64), ((g >> np.uint64(30)) & np.uint64(WIDTH - 1)).astype(np.int64)


def sketch(frame: DataFrame, window: int, gram: int) -> np.ndarray:
    """Bits of both rows of the merged sketch: is the counter two or more? Fixed size: 2 * WIDTH / 8 bytes."""

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def flush():
            g = np.concatenate(held)
            for r, cells in enumerate(_rows(g)):
                u, c = np.unique(cells, return_counts=True)
                code = ((u % SLAB).astype(np.uint32) << np.uint32(1)) | (c > 1).astype(np.uint32)
                cut = np.searchsorted(u, np.arange(0, WIDTH + SLAB, SLAB))
                at = [k for k in range(len(cut) - 1) if cut[k] < cut[k + 1]]
                yield pa.record_batch({"slab": pa.array([r * (WIDTH // SLAB) + k for k in at], pa.int64()), "body": pa.array([code[cut[k] : cut[k + 1]].tobytes() for k in at], pa.binary())})

        for b in W.slices(batches):
            words = W.Words(b.column(0))
            g, low, ok = _grams(words, window, gram)
            if not ok.any():
                continue
            w = window - gram + 1
            most = np.concatenate((np.zeros(w - 1, np.uint64), np.where(ok, low, np.uint64(0)), np.zeros(w - 1, np.uint64)))
            pick = g[W.sliding(most, w, np.maximum) == g]
            held.append(pick)
            n += len(pick)
            if n > 1_000_000:
                yield from flush()
                held, n = [], 0
        if n:
            yield from flush()

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, own = np.zeros(SLAB, np.uint8), None

        def done():
            return pa.record_batch({"slab": pa.array([own], pa.int64()), "body": pa.array([np.packbits(seen > 1, bitorder="little").tobytes()], pa.binary())})

        for b in batches:  # sorted by slab, so one slab's counters are held at a time
            for k, body in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if k != own:
                    if own is not None:
                        yield done()
                    own, seen[:] = k, 0
                x = np.frombuffer(body.as_buffer(), np.uint32)
                at = x >> np.uint32(1)
                seen[at] = np.minimum(seen[at] + 1 + (x & np.uint32(1)).astype(np.uint8), 2)
        if own is not None:
            yield done()
        W.trim()

    schema = "slab long, body binary"
    bits = np.zeros(2 * WIDTH // 8, np.uint8)
    merged = frame.select("text").mapInArrow(part, schema).repartition("slab").sortWithinPartitions("slab").mapInArrow(merge, schema)
    for r in merged.toLocalIterator():
        at = r["slab"] * (SLAB // 8)
        bits[at : at + SLAB // 8] = np.frombuffer(bytes(r["body"]), np.uint8)
    return bits


def _set(bits: np.ndarray, g: np.ndarray) -> np.ndarray:
    a, b = _rows(g)
    b = b + WIDTH
    one = ((bits[a >> 3] >> (a & 7).astype(np.uint8)) & 1).astype(bool)
    return one & ((bits[b >> 3] >> (b & 7).astype(np.uint8)) & 1).astype(bool)


def _differ(e: np.ndarray, *columns: str) -> np.ndarray:
    """Per entry: does it differ from the one before in any of the columns?"""
    new = np.ones(len(e), bool)
    if len(e):
        new[1:] = np.logical_or.reduce([e[c][1:] != e[c][:-1] for c in columns])
    return new


def _differ_by(e: np.ndarray, by: np.ndarray, column: str) -> np.ndarray:
    """_differ() of one column of e[by], which is not made whole."""
    x, new = e[column][by], np.ones(len(by), bool)
    new[1:] = x[1:] != x[:-1]
    return new


def _only(e: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """e[rows] of ascending rows, in the place of ``e``: no second copy of all columns."""
    for c in e.dtype.names:
        e[c][: len(rows)] = e[c][rows]
    return e[: len(rows)]


def _settled(e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which entries are of windows that occur twice or more in ``e`` and not known to repeat yet; one of each distinct window, marked."""
    by = np.argsort(np.ascontiguousarray(e["h1"]), kind="stable")
    new = _differ_by(e, by, "h1")
    every = new | _differ_by(e, by, "g") | _differ_by(e, by, "h2")
    if (every != new).any():  # one hash, several windows
        by = np.lexsort((e["h2"], e["h1"], e["g"]))
        every = _differ_by(e, by, "h1") | _differ_by(e, by, "g") | _differ_by(e, by, "h2")
    begin = np.flatnonzero(every)
    size = np.diff(np.append(begin, len(e)))
    hits = np.sort(by[np.repeat(size > 1, size) & ~e["known"][by]])
    first = by[begin]
    e["known"][first] |= size > 1
    return hits, np.sort(first)


def _stretches(e: np.ndarray, *same: str) -> tuple[np.ndarray, np.ndarray]:
    """Begins and lengths of runs of neighbouring starts of one document that agree in ``same``."""
    new = _differ(e, "dk", "th", *same)
    new[1:] |= e["pos"][1:] != e["pos"][:-1] + 1
    begin = np.flatnonzero(new)
    return begin, np.diff(np.append(begin, len(e)))


def _spots(hits: np.ndarray) -> dict[str, pa.Array]:
    """Columns of SPOTS."""
    begin, n = _stretches(hits)
    return {"dk": pa.array(hits["dk"][begin]), "th": pa.array(hits["th"][begin]), "pos": pa.array(hits["pos"][begin]), "n": pa.array(n.astype(np.int32))}


def repeated_windows(keys: DataFrame, window: int, gram: int = GRAM) -> DataFrame:
    """(dk, th, pos, n): runs of ``n`` window starts from ``pos`` on that also start anywhere else."""
    bits = keys.sparkSession.sparkContext.broadcast(sketch(keys, window, gram))

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in W.slices(batches, limit=2 * W.SLICE_BYTES):
            words = W.Words(b.column(0))
            _, low, ok = _grams(words, window, gram)
            pos = np.flatnonzero(ok)
            pos = pos[_set(bits.value, low[pos])]
            if not len(pos):
                continue
            e = np.zeros(len(pos), _ENTRY)
            e["g"] = low[pos].view(np.int64)
            del low, ok
            e["h1"] = W.rolling(words.hashes(11), window)[pos]
            e["h2"] = W.rolling(words.hashes(12), window, 0xD6E8FEB86659FD93)[pos] >> np.uint64(32)
            row = words.rows()[pos]
            e["dk"], e["th"], e["pos"] = b.column(1).to_numpy()[row], b.column(2).to_numpy()[row], pos - words.starts[row]
            del words, row, pos
            # what repeats within the slice is settled here; one entry marked as known tells the others
            hits, left = _settled(e)
            own = _spots(e[hits])
            k = len(own["dk"])
            deal = W.mix(own["dk"].to_numpy().view(np.uint64) + own["pos"].to_numpy().astype(np.uint64)).view(np.int64)
            yield pa.record_batch({"g": pa.array(deal), "known": pa.nulls(k, pa.bool_()), **own, "body": pa.nulls(k, pa.binary())})
            left = _only(e, left)
            begin, n = _stretches(left, "g", "known")
            ends = (np.append(begin, len(left)) * _HASH.itemsize).astype(np.int32)
            packed = np.empty(len(left), _HASH)
            packed["h1"], packed["h2"] = left["h1"], left["h2"]
            body = pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer(ends), pa.py_buffer(packed)])
            first = left[begin]
            yield pa.record_batch({**{c: pa.array(first[c]) for c in ("g", "known", "dk", "th", "pos")}, "n": pa.array(n.astype(np.int32)), "body": body})

    def resolve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        carry = np.zeros(0, _ENTRY)
        for b in batches:
            settled = b.column(6).is_null()
            yield pa.record_batch({c: b.column(2 + k) for k, c in enumerate(("dk", "th", "pos", "n"))}).filter(settled)
            b = b.filter(pc.invert(settled))
            if not b.num_rows:
                continue
            n = b.column(5).to_numpy()
            e = np.zeros(int(n.sum()), _ENTRY)
            packed = np.frombuffer(b"".join(x.as_buffer() for x in b.column(6)), _HASH)
            e["h1"], e["h2"] = packed["h1"], packed["h2"]
            for c, k in (("g", 0), ("dk", 2), ("th", 3)):
                e[c] = np.repeat(b.column(k).to_numpy(), n)
            e["known"] = np.repeat(b.column(1).to_numpy(zero_copy_only=False), n)
            e["pos"] = W.runs(b.column(4).to_numpy().astype(np.int64), n.astype(np.int64))
            last = e["g"][-1]
            e = np.concatenate((carry, e))
            hits, left = _settled(e)
            if len(hits):
                yield pa.record_batch(_spots(e[hits]))
            carry = e[left[e["g"][left] == last]]  # rows come by gram: only the last one may go on
            del e, packed
        W.trim()

    flagged = keys.select("text", "dk", "th").mapInArrow(part, "g long, known boolean, dk long, th long, pos int, n int, body binary")
    return flagged.repartition("g").sortWithinPartitions("g").mapInArrow(resolve, SPOTS)


def kept_words(words: list[bytes], pos: np.ndarray, n: np.ndarray, window: int) -> list[bytes]:
    """The words that no window covers, of those that start in the runs (pos, n)."""
    step = np.zeros(len(words) + 1, np.int64)
    np.add.at(step, pos, 1)
    np.add.at(step, pos + n + window - 1, -1)
    return [words[i] for i in np.flatnonzero(np.cumsum(step[:-1]) == 0).tolist()]


def dedup_substrings(frame: DataFrame, window: int = WINDOW, carry: list[str] | None = None) -> DataFrame:
    """Each row of ``frame`` (doc_id, text, ``carry``) with n_words, n_removed, kept_sha256 and kept (its remaining text).

    Every word covered by a window of ``window`` words that also starts anywhere else (same text included) goes.
    ``kept`` is null where nothing was removed. Null texts have no words; repeated rows repeat each other. Of an empty
    frame nothing comes back. ``carry`` may not name one of the columns made here.
    """
    carry = carry or []
    if {"doc_id", "n_words", "n_removed", "kept_sha256", "kept"} & set(carry):
        raise ValueError("a carried column has the name of a result")
    keys = W.keyed(frame)
    hits = repeated_windows(keys, window).groupBy("dk", "th").agg(F.collect_set(F.struct("pos", "n")).alias("spots"))
    own = frame.select(*(F.col(c).alias(f"c{i}") for i, c in enumerate(carry)), "doc_id", "text")
    own = own.withColumns({"dk": F.coalesce("doc_id", F.lit(W.NO_ID)).cast("long"), "th": F.xxhash64(F.coalesce("text", F.lit("")))})
    joined = own.join(hits, ["dk", "th"], "left")
    names = [f"c{i}" for i in range(len(carry))]
    fields = [f"{c} {frame.schema[o].dataType.simpleString()}" for c, o in zip(names, carry, strict=True)]

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in W.slices(batches):
            n, gone, sha, kept = [], [], [], []
            texts, spots = b.column(b.schema.get_field_index("text")), b.column(b.schema.get_field_index("spots"))
            pos, runs = (x.to_numpy().astype(np.int64) for x in spots.flatten().flatten())
            cut = np.concatenate(([0], np.cumsum(pc.fill_null(pc.list_value_length(spots), 0).to_numpy())))
            for r, t in enumerate(texts):
                raw = t.as_buffer()
                words = raw.to_pybytes().split() if raw is not None else []
                lo, hi = cut[r], cut[r + 1]
                left = kept_words(words, pos[lo:hi], runs[lo:hi], window) if hi > lo else words
                body = b" ".join(left)
                n.append(len(words))
                gone.append(len(words) - len(left))
                sha.append(hashlib.sha256(body).hexdigest())
                kept.append(body.decode() if gone[-1] else None)
            yield pa.record_batch({**{c: b.column(b.schema.get_field_index(c)) for c in names}, "doc_id": b.column(b.schema.get_field_index("doc_id")), "n_words": pa.array(n, pa.int64()), "n_removed": pa.array(gone, pa.int64()), "kept_sha256": pa.array(sha, pa.string()), "kept": pa.array(kept, pa.string())})

    id_type = frame.schema["doc_id"].dataType.simpleString()
    out = joined.select(*names, "doc_id", "text", "spots").mapInArrow(finish, ", ".join([*fields, f"doc_id {id_type}", "n_words long", "n_removed long", "kept_sha256 string", "kept string"]))
    return out.withColumnsRenamed(dict(zip(names, carry, strict=True)))


def op4_substring_dedup(spark, sf_dir) -> DataFrame:
    return dedup_substrings(W.docs(spark, sf_dir)).drop("kept")
