"""Token-id files: static range asymmetric numeral coding in independent blocks of interleaved lanes.

One frequency table, counted over all texts, serves all blocks. A block holds whole documents; its ids are dealt
row-wise to LANES lanes that are coded in step. Every CHECK rows a checkpoint keeps the lane states and the place in
the word stream, so a decoder may start there; a checksum of the block's ids is verified on reading. Blocks are rows of
Parquet files, written in ascending doc_id order through Spark's committer, so a lost task leaves nothing half-written.
"""

from __future__ import annotations

import json
import os
import re
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.llm import words as W

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
SCALE, LANES, CHECK, BLOCK = 20, 1024, 256, 1 << 20
LOW = np.uint64(1 << 31)
END_ID = 2
_HEAD = struct.Struct("<4sHHQQII")  # magic, version, lanes, ids, words, checkpoints, crc32 of the ids


class Codec:
    """Coding tables for ``freq``, positive integers that sum to 2**SCALE."""

    def __init__(self, freq: np.ndarray):
        self.freq = freq.astype(np.uint64)
        self.cum = np.concatenate(([0], np.cumsum(self.freq)[:-1])).astype(np.uint64)
        self.symbol = np.repeat(np.arange(len(freq), dtype=np.uint32), freq.astype(np.int64))

    @staticmethod
    def table(counts: np.ndarray) -> np.ndarray:
        """Counts scaled to sum to 2**SCALE, at least 1 each, so that every id can be coded."""
        total = 1 << SCALE
        room = total - len(counts)
        share = counts.astype(np.float64) / max(1, counts.sum())
        freq = 1 + np.floor(share * room).astype(np.int64)
        freq[int(np.argmax(counts))] += total - int(freq.sum())
        return freq

    def encode(self, ids: np.ndarray) -> bytes:
        n = len(ids)
        lanes = int(min(LANES, max(1, n)))
        rows = -(-n // lanes)
        padded = np.zeros(rows * lanes, np.int64)
        padded[:n] = ids
        grid = padded.reshape(rows, lanes)
        x = np.full(lanes, LOW)
        words, marks, count = [], [], 0
        shift, top = np.uint64(SCALE), np.uint64(63 - SCALE)
        for r in range(rows - 1, -1, -1):
            f = self.freq[grid[r]]
            over = (x >> top) >= f
            if over.any():
                out = x[over].astype(np.uint32)
                words.append(out)
                count += len(out)
                x = np.where(over, x >> np.uint64(32), x)
            q = x // f
            x = (q << shift) + (x - q * f) + self.cum[grid[r]]
            if r and r % CHECK == 0:
                marks.append((r, count, x.astype("<u8").tobytes()))
        body = np.concatenate(words[::-1]).astype("<u4").tobytes() if words else b""
        head = _HEAD.pack(b"RANS", 1, lanes, n, count, len(marks), zlib.crc32(ids.astype("<u4").tobytes()))
        checks = b"".join(struct.pack("<QQ", r, count - c) + s for r, c, s in reversed(marks))
        return head + x.astype("<u8").tobytes() + checks + body

    def decode(self, block: bytes, start_row: int = 0, rows: int | None = None) -> np.ndarray:
        """All ids of a block, or those of ``rows`` rows from the checkpoint at ``start_row`` on. Checks the checksum of all."""
        magic, version, lanes, n, count, marks, crc = _HEAD.unpack_from(block)
        if magic != b"RANS" or version != 1:
            raise ValueError("not a block of this format")
        at = _HEAD.size
        x = np.frombuffer(block, "<u8", lanes, at).astype(np.uint64)
        at += 8 * lanes
        pos, every = 0, -(-n // lanes)
        for k in range(marks):
            r, used = struct.unpack_from("<QQ", block, at + k * (16 + 8 * lanes))
            if r == start_row:
                x = np.frombuffer(block, "<u8", lanes, at + k * (16 + 8 * lanes) + 16).astype(np.uint64)
                pos = used
        words = np.frombuffer(block, "<u4", count, at + marks * (16 + 8 * lanes)).astype(np.uint64)
        last = every if rows is None else min(every, start_row + rows)
        out = np.empty((max(0, last - start_row), lanes), np.uint32)
        mask, shift = np.uint64((1 << SCALE) - 1), np.uint64(SCALE)
        for r in range(last - start_row):
            slot = x & mask
            s = self.symbol[slot]
            out[r] = s
            x = self.freq[s] * (x >> shift) + slot - self.cum[s]
            low = x < LOW
            k = int(low.sum())
            if k:
                x[low] = (x[low] << np.uint64(32)) | words[pos : pos + k]
                pos += k
        ids = out.reshape(-1)[: n - start_row * lanes]
        if last == every and n and (x != LOW).any():
            raise ValueError("a token block does not end in the coder's first state")
        if start_row == 0 and last == every and zlib.crc32(ids.astype("<u4").tobytes()) != crc:
            raise ValueError("checksum of a token block does not match")
        return ids


class WordIds:
    """Token ids of white-space words, put together from those of their pre-tokens, which are few and kept (KEEP at most).

    The tokenizer drops white space and codes each pre-token on its own, so a text's ids are those of its words in order,
    and a word's those of its pre-tokens. Words with ODD characters, or with what could be a special token, are
    given to the library whole; the pre-tokens too are coded by the library.
    """

    KEEP = 1_000_000
    ODD = r"[^\x00-\x{24F}]|[\x1c-\x1f\x{85}\x{A0}]"  # characters past the Latin blocks, and white space that does not cut words here
    PLAIN = re.compile(r"\n|'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\na-z0-9]+")
    WIDE = regex.compile(r"\n|'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.vocab_size = self.tok.get_vocab_size()
        self.width = np.uint16 if self.vocab_size <= 1 << 16 else np.uint32
        ends = [i for t, i in self.tok.get_vocab().items() if t.endswith("</w>")]
        self.ends = np.zeros(self.vocab_size, bool)
        self.ends[ends] = True
        self.split = self._splits()
        self.forget()

    def _splits(self) -> bool:
        """Does the file cut words as WIDE does? Else every word goes to the library whole."""
        own = json.loads(self.tok.to_str())
        kinds = [x["type"] for x in own["normalizer"]["normalizers"]] if (own["normalizer"] or {}).get("type") == "Sequence" else []
        cuts = (own["pre_tokenizer"] or {}).get("pretokenizers", [{}])[0].get("pattern", {}).get("Regex", "").replace("[\\p{L}]", "\\p{L}").replace("[\\p{N}]", "\\p{N}")
        return kinds == ["NFC", "Replace", "Lowercase"] and "\\n|" + cuts == self.WIDE.pattern and bool(self.ends.any())

    def forget(self) -> None:
        self.known: dict[str, int] = {}
        self.flat, self.cut = np.zeros(1 << 16, self.width), np.zeros(1 << 14, np.int64)
        self.used = 0

    def _learn(self, new: list[str]) -> None:
        """Ids of strings not yet known, coded in one call where the ends of words tell them apart."""
        ids = np.array(self.tok.encode(" ".join(new), add_special_tokens=False).ids, self.width) if self.split else np.zeros(0, self.width)
        stops = np.flatnonzero(self.ends[ids]) + 1
        if not self.split or len(stops) != len(new):
            each = [np.array(e.ids, self.width) for e in self.tok.encode_batch_fast(new, add_special_tokens=False)]
            ids, stops = np.concatenate(each), np.cumsum([len(e) for e in each])
        k, n = len(self.known), len(new)
        while self.used + len(ids) > len(self.flat):
            self.flat = np.concatenate((self.flat, np.zeros_like(self.flat)))
        while k + n >= len(self.cut):
            self.cut = np.concatenate((self.cut, np.zeros_like(self.cut)))
        self.flat[self.used : self.used + len(ids)] = ids
        self.cut[k + 1 : k + n + 1] = self.used + stops
        self.used += len(ids)
        self.known.update(zip(new, range(k, k + n), strict=True))

    def _places(self, parts: list[str]) -> np.ndarray:
        get = self.known.get
        at = np.fromiter((get(x, -1) for x in parts), np.int64, len(parts))
        if (at < 0).any():
            new = list(dict.fromkeys(parts[i] for i in np.flatnonzero(at < 0).tolist()))
            for lo in range(0, len(new), 50_000):
                self._learn(new[lo : lo + 50_000])
            at = np.fromiter((get(x, -1) for x in parts), np.int64, len(parts))
        return at

    def of(self, vocab: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words one after another, and each word's number of ids."""
        if len(self.known) > self.KEEP:
            self.forget()
        n = len(vocab)
        if not n:
            return np.zeros(0, self.width), np.zeros(0, np.int64)
        words = pa.array(vocab, pa.large_string())
        odd = pc.or_(pc.match_substring(words, "<|"), pc.match_substring_regex(words, self.ODD))
        ascii_only = pc.string_is_ascii(words)
        kinds = (pc.and_not(ascii_only, odd), pc.and_not(pc.invert(ascii_only), odd), odd)
        plain, wide, whole = (np.flatnonzero(k.to_numpy(zero_copy_only=False)) for k in (kinds if self.split else (pc.and_not(odd, odd),) * 2 + (pc.or_(odd, pc.invert(odd)),)))
        # without ODD characters nothing is composed anew and lower case goes character by character, as in the library
        parts = self.PLAIN.findall("\n".join(W.strings(words.take(plain))).lower()) if len(plain) else []
        if len(plain) and len(wide):
            parts.append("\n")
        parts += self.WIDE.findall("\n".join(W.strings(words.take(wide))).lower()) if len(wide) else []
        coded = pc.dictionary_encode(pa.array(parts, pa.large_string()))
        seen, which = W.strings(coded.dictionary), coded.indices.to_numpy(zero_copy_only=False)
        mark = seen.index("\n") if "\n" in seen else -1
        place = self._places([x for x in seen if x != "\n"])
        if mark >= 0:
            place = np.insert(place, mark, -1)
        word = np.cumsum(which == mark) if len(which) else np.zeros(0, np.int64)
        kept = which != mark
        order = np.concatenate((plain, wide, whole))  # the source holds the words in this order
        part_place, part_word = place[which[kept]], order[word[kept]]
        each = [np.array(e.ids, self.width) for e in self.tok.encode_batch_fast(W.strings(words.take(whole)), add_special_tokens=False)] if len(whole) else []
        length = self.cut[part_place + 1] - self.cut[part_place]
        extra = np.fromiter(map(len, each), np.int64, len(each))
        size = np.bincount(part_word, length, n).astype(np.int64)
        size[whole] = extra
        own = self.flat[W.runs(self.cut[part_place], length)]
        source = np.concatenate([own, *each]) if each else own
        begin = np.zeros(n, np.int64)
        begin[order] = np.cumsum(size[order]) - size[order]
        return source[W.runs(begin, size)], size


_open: dict[str, WordIds] = {}


def _words_of(path: str) -> WordIds:
    if path not in _open:
        _open[path] = WordIds(path)
    return _open[path]


def encoded_slice(w: W.Words, words: WordIds, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all rows of a slice, ``end_id`` after each row, and each row's number of ids."""
    flat, size = words.of(w.vocab)
    begin = (np.cumsum(size) - size).astype(np.int64)
    per = size[w.codes]
    total = np.concatenate(([0], np.cumsum(per)))
    row_ends = total[w.starts[1:]]
    n = np.diff(total[w.starts]) + 1
    ids = flat[W.runs(begin[w.codes], per)]
    kind = words.width if end_id <= np.iinfo(words.width).max else np.uint32
    return np.insert(ids.astype(kind, copy=False), row_ends, end_id), n


def encoded(frame: DataFrame, path: str, end_id: int) -> DataFrame:
    """(doc_id, th, ids): each row's ids, packed with 16 bits an id where the vocabulary allows, else 32. Texts are coded once, here."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = _words_of(path)
        for b in W.slices(batches, limit=4 * W.SLICE_BYTES):
            ids, n = encoded_slice(W.Words(b.column(1)), words, end_id)
            ids = ids.astype(id_type(words.vocab_size, end_id), copy=False)
            ends = np.concatenate(([0], np.cumsum(n))) * ids.itemsize
            body = pa.Array.from_buffers(pa.large_binary(), len(n), [None, pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(ids))])
            yield pa.record_batch({"doc_id": b.column(0), "th": b.column(2), "ids": body.cast(pa.binary())})

    rows = frame.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("th", F.xxhash64(F.coalesce("text", F.lit(""))))
    return rows.mapInArrow(run, "doc_id long, th long, ids binary")


def id_type(vocab_size: int, end_id: int) -> type:
    return np.uint16 if max(vocab_size, end_id + 1) <= 1 << 16 else np.uint32


def _flat(col: pa.Array, kind: type) -> tuple[np.ndarray, np.ndarray]:
    """All ids of a column of packed ids, and the number of ids of each row."""
    offs = np.frombuffer(col.buffers()[1], np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    return np.frombuffer(col.buffers()[2], np.uint8)[offs[0] : offs[-1]].view(kind), np.diff(offs) // np.dtype(kind).itemsize


def token_counts(coded: DataFrame, size: int, kind: type) -> np.ndarray:
    """How often each id occurs in all rows of ``coded``."""

    def fill(mine, b):
        mine += np.bincount(_flat(b.column(0), kind)[0], minlength=size)

    return W.summed_sketch(coded.select("ids"), size, fill, text="ids")


def write_tokens(frame: DataFrame, folder: str, path: str | None = None, end_id: int = END_ID) -> None:
    """Write the token ids of all rows of (doc_id, text) into ``folder``, ascending by doc_id (null first; ties by text hash).

    Null texts are empty; each document ends with ``end_id``. ``folder``/blocks has (part, block, start, docs, sizes,
    payload), ``folder``/table the frequency table. The coded rows wait in the shared folder and go when the blocks are written.
    """
    path = W.tokenizer_path("word_bpe_49k.json", path)
    size = max(WordIds(path).vocab_size, end_id + 1)
    kind = id_type(size, end_id)
    spark = frame.sparkSession
    coded = W.written(encoded(frame, path, end_id), "ids")
    freq = Codec.table(token_counts(coded, size, kind))
    spark.createDataFrame([(freq.astype("<u4").tobytes(),)], "freq binary").coalesce(1).write.parquet(f"{folder}/table")
    table = spark.sparkContext.broadcast(freq)
    ordered = coded.repartitionByRange(W.partitions(spark), "doc_id").sortWithinPartitions("doc_id", "th").select("doc_id", "ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, part, k, start = Codec(table.value), TaskContext.get().partitionId(), 0, 0
        for b in batches:
            if not b.num_rows:
                continue
            ids, n = _flat(b.column(1), kind)
            ends = np.cumsum(n)
            at = 0
            while at < len(n):
                base = int(ends[at - 1]) if at else 0
                to = max(at + 1, int(np.searchsorted(ends, base + BLOCK, side="right")))
                mine = ids[base : int(ends[to - 1])].astype(np.uint32)
                row = {"part": pa.array([part], pa.int32()), "block": pa.array([k], pa.int64()), "start": pa.array([start], pa.int64()), "n_ids": pa.array([len(mine)], pa.int64())}
                row["docs"] = pa.array([b.column(0).slice(at, to - at).to_pylist()], pa.list_(pa.int64()))
                row["sizes"] = pa.array([n[at:to].tolist()], pa.list_(pa.int64()))
                yield pa.record_batch(row | {"payload": pa.array([codec.encode(mine)], pa.binary())})
                at, k, start = to, k + 1, start + len(mine)

    ordered.mapInArrow(run, "part int, block long, start long, n_ids long, docs array<long>, sizes array<long>, payload binary").write.parquet(f"{folder}/blocks")
    W.dropped(coded)


def read_tokens(spark, folder: str, with_ids: bool = True) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of each document in the files; start: ids of all documents before it."""
    freq = np.frombuffer(bytes(spark.read.parquet(f"{folder}/table").first()["freq"]), "<u4").astype(np.int64)
    blocks = spark.read.parquet(f"{folder}/blocks")
    parts = sorted((r["part"], r["n"]) for r in blocks.groupBy("part").agg(F.sum("n_ids").alias("n")).collect())  # one row a write task
    before, offsets = 0, {}
    for p, n in parts:
        offsets[p], before = before, before + n
    held = spark.sparkContext.broadcast((freq, offsets))
    names = ["docs", "sizes", "payload", "part", "start"]

    def run(batches):
        codec = Codec(held.value[0])
        for b in batches:
            for r in range(b.num_rows):
                docs, sizes, payload, part, start = (b.column(b.schema.get_field_index(c))[r] for c in names)
                ids = codec.decode(payload.as_buffer().to_pybytes())
                n = sizes.values.to_numpy().astype(np.int64)
                cut = np.concatenate(([0], np.cumsum(n)))
                raw = ids.astype("<u4").tobytes()
                cols = {"doc_id": docs.values, "start": pa.array(cut[:-1] + start.as_py() + held.value[1][part.as_py()]), "n_tokens": pa.array(n), "ids_crc32": pa.array([zlib.crc32(raw[4 * a : 4 * e]) for a, e in zip(cut[:-1], cut[1:], strict=True)], pa.int64())}
                if with_ids:
                    cols["ids"] = pa.ListArray.from_arrays(pa.array(cut.astype(np.int32)), pa.array(ids.astype(np.int32)))
                yield pa.record_batch(cols)

    return blocks.select(*names).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<int>" * with_ids)


def op6_token_files(spark, sf_dir) -> DataFrame:
    folder = f"{W.shared(spark)}/tokens-{uuid.uuid4().hex}"
    write_tokens(W.docs(spark, sf_dir), folder)
    return read_tokens(spark, folder, with_ids=False)
