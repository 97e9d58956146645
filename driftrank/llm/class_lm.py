"""Class-based bigram language model: exchange clustering, class transitions and word emissions.

Texts are coded once, slice by slice: word numbers and the slice's distinct words by 64-bit hash. The CORE most frequent
words are put into CLASSES classes by the exchange algorithm, word after word until none moves. Every other word that
occurs LEAST times or more then moves to the class that the exchange criterion prefers, given the core's classes and its
own neighbours over all texts; rarer words and unknown ones share the class RARE. The word table (hash, count, class)
grows with the corpus, is never broadcast and never reaches the driver: it is joined with each slice's distinct words.
P(word | previous word) = LAMBDA * P(class | previous class) * P(word | class) + (1 - LAMBDA) * add-one unigram; it sums
to 1 over the known words and one unknown word.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftrank.llm import words as W

CORE, CLASSES, LEAST, SWEEPS = 1500, 48, 2, 20
LAMBDA, STRENGTH = 0.95, 5.0
END, RARE = 0, 1  # classes; exchange classes follow
KINDS = 2 + CLASSES
MERGED = 4  # slices whose words are put together before they travel
SMALL = 16  # neighbour counts whose gains are tabled


def _hash(vocab: list[str]) -> np.ndarray:
    return np.fromiter((xxhash.xxh3_64_intdigest(v, 3) for v in vocab), np.uint64, len(vocab)).view(np.int64)


def _packed(x: np.ndarray, kind: str) -> pa.Array:
    return pa.array([x.astype(kind).tobytes()], pa.binary())


def _unpacked(b: pa.RecordBatch, name: str, r: int, kind: str) -> np.ndarray:
    raw = b.column(b.schema.get_field_index(name))[r].as_buffer()
    return np.frombuffer(raw if raw is not None else b"", kind)


def _planes(codes: np.ndarray) -> dict[str, pa.Array]:
    """Word numbers as low and high halves: frequent words come early, so the high halves are mostly 0 and pack well."""
    return {"low": _packed(codes & 0xFFFF, "<u2"), "high": _packed(codes >> 16, "<u2")}


def _codes(b: pa.RecordBatch, r: int) -> np.ndarray:
    return _unpacked(b, "low", r, "<u2").astype(np.int64) | _unpacked(b, "high", r, "<u2").astype(np.int64) << 16


def coded(documents: DataFrame, learn: Column) -> DataFrame:
    """One row a slice of (doc_id, text) rows: slice, ids, learn, starts, low and high (word numbers), hashes (of the distinct words).

    ``learn`` says which rows may be learnt from; null counts as no. Null texts have no words.
    """
    kind = documents.schema["doc_id"].dataType.simpleString()

    def run(batches):
        at = TaskContext.get().partitionId() << 32
        for b in W.slices(batches, limit=4 * W.SLICE_BYTES):
            w = W.Words(b.column(1), lower=True)
            row = {"slice": pa.array([at], pa.int64()), "ids": pa.ListArray.from_arrays(pa.array([0, b.num_rows], pa.int32()), b.column(0)), "learn": _packed(b.column(2).to_numpy(zero_copy_only=False), "?")}
            yield pa.record_batch(row | {"starts": _packed(w.starts, "<i8"), **_planes(w.codes), "hashes": _packed(_hash(w.vocab), "<i8")})
            at += 1

    rows = documents.select("doc_id", "text", F.coalesce(learn, F.lit(False)).alias("learn"))
    return rows.mapInArrow(run, f"slice long, ids array<{kind}>, learn binary, starts binary, low binary, high binary, hashes binary")


def _sequence(b: pa.RecordBatch, r: int, of: str = "hashes", kind: str = "<i8") -> tuple[np.ndarray, np.ndarray]:
    """Word codes of a slice's learnt rows with -1 (an end) before each row and after the last, and a column of its words."""
    starts, codes, learn = _unpacked(b, "starts", r, "<i8"), _codes(b, r), _unpacked(b, "learn", r, "?")
    size = np.where(learn, np.diff(starts), 0)
    own = codes[W.runs(starts[:-1][learn], np.diff(starts)[learn])]
    seq = np.full(len(own) + int(learn.sum()) + 1, -1)
    seq[np.arange(len(own)) + np.repeat(np.arange(int(learn.sum())), size[learn]) + 1] = own
    return seq, _unpacked(b, of, r, kind)


def word_counts(slices: DataFrame) -> DataFrame:
    """(h, c) of all words of the learnt rows, the end token not included."""

    def run(batches):
        for b in batches:
            for r in range(b.num_rows):
                seq, h = _sequence(b, r)
                n = np.bincount(seq[seq >= 0], minlength=len(h))
                yield pa.record_batch({"h": pa.array(h[n > 0]), "c": pa.array(n[n > 0])})

    return slices.mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))


def _f(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1))


def exchange(pairs: np.ndarray, fixed: np.ndarray, classes: int, sweeps: int = SWEEPS) -> np.ndarray:
    """Class of each symbol, from bigram counts; ``fixed`` >= 0 pins a symbol. Maximises the class bigram likelihood.

    Movable symbols start in round-robin order (given by falling count) and move, one after another, to the class that
    raises sum f(class pair count) - 2 * sum f(class count) most, f(x) = x log x, until a sweep changes nothing (or ``sweeps`` are over).
    """
    n = len(pairs)
    pinned = int(fixed.max()) + 1 if (fixed >= 0).any() else 0
    total = pinned + classes
    cls = fixed.copy()
    free = np.flatnonzero(fixed < 0)
    cls[free] = pinned + np.arange(len(free)) % classes
    pairs = pairs.astype(np.float64)
    g = np.zeros((total, total))
    np.add.at(g, (np.repeat(cls, n), np.tile(cls, n)), pairs.ravel())
    row, col = pairs.sum(1), pairs.sum(0)
    back = pairs.T.copy()
    for _ in range(sweeps):
        moved = 0
        for w in free.tolist():
            old = cls[w]
            own = pairs[w, w]
            out = np.bincount(cls, pairs[w], total)
            out[old] -= own
            into = np.bincount(cls, back[w], total)
            into[old] -= own
            g[old] -= out
            g[:, old] -= into
            g[old, old] -= own
            r, c = g.sum(1), g.sum(0)
            gain = (_f(g + out) - _f(g)).sum(1) + (_f(g + into[:, None]) - _f(g)).sum(0)
            d = np.diag(g)
            gain += _f(d + out + into + own) - _f(d + out) - _f(d + into) + _f(d)
            gain -= _f(r + row[w]) - _f(r) + _f(c + col[w]) - _f(c)
            gain[:pinned] = -np.inf
            new = int(np.argmax(gain))
            if gain[new] <= gain[old] + 1e-9:
                new = int(old)
            moved += new != old
            cls[w] = new
            g[new] += out
            g[:, new] += into
            g[new, new] += own
        if not moved:
            break
    return cls


def _core_symbols(h: np.ndarray, known: np.ndarray, values: np.ndarray, other: int) -> np.ndarray:
    """``values`` of the hashes found in ``known`` (ascending), ``other`` for all others."""
    if not len(known):
        return np.full(len(h), other)
    at = np.minimum(np.searchsorted(known, h), len(known) - 1)
    return np.where(known[at] == h, values[at], other)


def class_pairs(slices: DataFrame, known, cells: int, end: int, other: int) -> np.ndarray:
    """Counts of neighbouring symbols, ``cells`` square; ``known`` broadcasts (hashes, symbols) of a bounded number of words."""

    def fill(mine, b):
        for r in range(b.num_rows):
            seq, h = _sequence(b, r)
            s = np.append(_core_symbols(h, *known.value, other), end)[seq]
            mine += np.bincount(s[:-1] * cells + s[1:], minlength=cells * cells)

    return W.summed_sketch(slices, cells * cells, fill, text="low").reshape(cells, cells)


class Gains:
    """The exchange criterion for words outside the core, from the class pair counts ``g`` of the core."""

    def __init__(self, g: np.ndarray):
        self.g, self.out, self.into = g, g.sum(1), g.sum(0)
        x = np.arange(SMALL)[:, None, None]
        # by count, neighbour class and own class: what f(pair count) gains
        self.right = (_f(g.T[None] + x) - _f(g.T[None])).transpose(0, 1, 2)
        self.left = _f(g[None] + x) - _f(g[None])

    def best(self, word: np.ndarray, side: np.ndarray, near: np.ndarray, n: np.ndarray, c: np.ndarray) -> np.ndarray:
        """The best class of each word: entries (word, side, neighbour class, count) come sorted by word; ``c``: counts of words."""
        gain = np.empty((len(word), KINDS))
        small = n < SMALL
        for s, table, g in ((0, self.left, self.g), (1, self.right, self.g.T)):
            at = np.flatnonzero(small & (side == s))
            gain[at] = table[n[at], near[at]]
            at = np.flatnonzero(~small & (side == s))
            gain[at] = _f(g[near[at]] + n[at, None]) - _f(g[near[at]])
        total = np.add.reduceat(gain, np.searchsorted(word, np.arange(len(c)))) if len(c) else gain[:0]
        x = c[:, None]
        total = total - (_f(self.out + x) - _f(self.out)) - (_f(self.into + x) - _f(self.into))
        return total[:, 2:].argmax(axis=1) + 2


def merged(slices: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes, byte offsets, neighbours), a row a word, of slices of (hashes, counts, two neighbours a count): a word travels once for all of them."""
    h, n, near = (np.concatenate(x) for x in zip(*slices))
    order = np.argsort(h, kind="stable")
    words, first = np.unique(h[order], return_index=True)
    near = near[W.runs((np.cumsum(n) - n)[order], n[order])]
    ends = np.concatenate(([0], np.cumsum(2 * n[order])))
    return words, np.append(ends[first], ends[-1]).astype(np.int32), np.ascontiguousarray(near)


def moved_words(slices: DataFrame, core, g: np.ndarray) -> DataFrame:
    """(h, c, cls) of all learnt words outside the core, by the classes of their neighbours in all texts.

    A word's neighbours come as one byte each; neighbours outside the core count as RARE. Rows are dealt and sorted by
    word, so a task holds a batch and one word's sums.
    """
    gains = slices.sparkSession.sparkContext.broadcast(Gains(g.astype(np.float64)))

    def part(batches):
        held = []

        def row():
            h, cut, near = merged(held)
            held.clear()
            return pa.record_batch({"h": pa.array(h), "near": pa.Array.from_buffers(pa.binary(), len(h), [None, pa.py_buffer(cut), pa.py_buffer(near)])})

        for b in batches:
            for r in range(b.num_rows):
                seq, h = _sequence(b, r)
                known, cls = core.value
                k = np.append(_core_symbols(h, known, cls, RARE), END).astype(np.uint8)[seq]
                mid = np.flatnonzero((seq >= 0) & (k == RARE))
                mid = mid[np.argsort(seq[mid], kind="stable")]
                near = np.stack((k[mid - 1], k[mid + 1]), 1)
                n = np.bincount(seq[mid], minlength=len(h))
                own = np.flatnonzero(n)
                held.append((h[own], n[own], near))
                if len(held) == MERGED:
                    yield row()
        if held:
            yield row()

    def sums(batches):
        last, held = None, np.zeros(2 * KINDS, np.int64)

        def told(h, cells):
            """Rows of words ``h`` from (word, side and class, count)."""
            word, cell, n = cells
            c = np.bincount(word[cell < KINDS], n[cell < KINDS], len(h)).astype(np.int64)
            cls = gains.value.best(word, cell // KINDS, cell % KINDS, n, c.astype(np.float64))
            return pa.record_batch({"h": pa.array(h), "c": pa.array(c), "cls": pa.array(np.where(c >= LEAST, cls, RARE).astype(np.int32))})

        for b in batches:
            if not b.num_rows:
                continue
            h = b.column(0).to_numpy()
            offs = np.frombuffer(b.column(1).buffers()[1], np.int32)[b.column(1).offset : b.column(1).offset + len(h) + 1].astype(np.int64)
            near = np.frombuffer(b.column(1).buffers()[2], np.uint8)[offs[0] : offs[-1]].astype(np.int64)
            near[1::2] += KINDS
            words, of = np.unique(h, return_inverse=True)  # ascending, as the rows are
            key, n = np.unique(np.repeat(of, np.diff(offs)) * (2 * KINDS) + near, return_counts=True)
            word, cell = key // (2 * KINDS), key % (2 * KINDS)
            if last is not None and last != words[0]:
                at = np.flatnonzero(held)
                yield told(np.array([last]), (np.zeros(len(at), np.int64), at, held[at]))
                held[:] = 0
            elif last is not None:
                own = word == 0
                held[cell[own]] += n[own]
            if last is None or last != words[0]:
                held[:] = 0
                held[cell[word == 0]] = n[word == 0]
            if len(words) > 1:  # the first word is whole now, the last one may go on
                at = np.flatnonzero(held)
                yield told(words[:1], (np.zeros(len(at), np.int64), at, held[at]))
                own = (word > 0) & (word < len(words) - 1)
                if own.any():
                    yield told(words[1:-1], (word[own] - 1, cell[own], n[own]))
                held[:] = 0
                held[cell[word == len(words) - 1]] = n[word == len(words) - 1]
            last = words[-1]
        if last is not None:
            at = np.flatnonzero(held)
            yield told(np.array([last]), (np.zeros(len(at), np.int64), at, held[at]))

    return slices.mapInArrow(part, "h long, near binary").repartition("h").sortWithinPartitions("h").mapInArrow(sums, "h long, c long, cls int")


class ClassModel:
    """``words``: table (h, c, cls) of all learnt words. ``trans``: P(class | previous class). ``size``, ``kinds``: tokens and distinct
    words of each class. ``n``, ``v``: tokens and distinct tokens, end tokens included."""

    def __init__(self, words: DataFrame, trans, size, kinds, n: int, v: int):
        self.words, self.trans, self.size, self.kinds, self.n, self.v = words, trans, size, kinds, n, v


def _by_slice(batches):
    """(slice, columns) of runs of rows of one slice, which may go on in the next run; rows come sorted by slice, the first column."""
    for b in batches:
        s = b.column(0).to_numpy()
        cut = np.flatnonzero(np.append(True, s[1:] != s[:-1])) if len(s) else []
        for lo, hi in zip(cut, [*cut[1:], len(s)], strict=True):
            yield int(s[lo]), [b.column(i).slice(lo, hi - lo) for i in range(1, b.num_columns)]


def _entries(c: np.ndarray, cls: np.ndarray) -> dict[str, pa.Array]:
    return {"c": _packed(c, "<i8" if len(c) and c.max() >= 1 << 32 else "<u4"), "cls": _packed(cls, "u1")}


def pieces(batches):
    """Rows (slice, k, c, cls), sorted by slice and k, as one row a slice: steps from one k to the next (low, high), counts and classes."""

    def row(at, held):
        k, c, cls = (np.concatenate(x) for x in zip(*held))
        return pa.record_batch({"slice": pa.array([at], pa.int64()), **_planes(np.diff(k.astype(np.int64), prepend=0)), **_entries(c, cls)})

    last, held = None, []
    for at, cols in _by_slice(batches):
        if at != last and held:
            yield row(last, held)
            held = []
        last = at
        held.append([x.to_numpy() for x in cols])
    if held:
        yield row(last, held)


def assembled(batches):
    """Rows of pieces(), sorted by slice, as one row a slice with the counts and classes of all its distinct words."""

    def row(at, held):
        k, c, cls = (np.concatenate(x) for x in zip(*held))
        order = np.empty(len(k), np.int64)
        order[k] = np.arange(len(k))
        return pa.record_batch({"slice": pa.array([at], pa.int64()), **_entries(c[order], cls[order])})

    last, held = None, []
    for b in batches:
        s = b.column(0).to_pylist()
        for r, at in enumerate(s):
            if at != last and held:
                yield row(last, held)
                held = []
            last = at
            cls, raw = _unpacked(b, "cls", r, "u1"), _unpacked(b, "c", r, "u1")
            held.append((np.cumsum(_codes(b, r)), raw.view("<u4" if len(raw) == 4 * len(cls) else "<i8").astype(np.int64), cls))
    if held:
        yield row(last, held)


def answers(slices: DataFrame, words: DataFrame) -> DataFrame:
    """(slice, c, cls), written: count and class of each distinct word of a slice (0 and RARE for unknown ones), packed.

    They go back to their slices in pieces, one of each slice and task.
    """

    def names(batches):
        for b in batches:
            for r in range(b.num_rows):
                h = _unpacked(b, "hashes", r, "<i8")
                yield pa.record_batch({"slice": pa.array(np.full(len(h), b.column(0)[r].as_py())), "k": pa.array(np.arange(len(h), dtype=np.int32)), "h": pa.array(h)})

    packed = "low binary, high binary, c binary, cls binary"
    found = slices.select("slice", "hashes").mapInArrow(names, "slice long, k int, h long").join(words, "h", "left")
    found = found.select("slice", "k", F.coalesce("c", F.lit(0)).alias("c"), F.coalesce("cls", F.lit(RARE)).alias("cls"))
    parts = found.sortWithinPartitions("slice", "k").mapInArrow(pieces, f"slice long, {packed}")
    return W.written(parts.repartition("slice").sortWithinPartitions("slice").mapInArrow(assembled, "slice long, c binary, cls binary"), "replies")


def answered(slices: DataFrame, replies: DataFrame) -> DataFrame:
    """``slices``, written, with their ``replies`` in place of their hashes; both are dropped."""
    ready = W.written(slices.drop("hashes").join(replies, "slice", "left"), "ready")  # a slice without words has no reply
    W.dropped(slices, replies)
    return ready


def train(documents: DataFrame, learn: Column | None = None) -> tuple[ClassModel, DataFrame]:
    """The model of the rows of (doc_id, text) that ``learn`` names (all, if none), and all rows coded with their words' entries.

    Null texts count as one end token each; of an empty frame the model knows nothing.
    """
    spark = documents.sparkSession
    slices = W.written(coded(documents, F.lit(True) if learn is None else learn), "coded")
    counts = W.written(word_counts(slices), "counts")
    s = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    top = counts.orderBy(F.col("c").desc(), "h").limit(CORE).toPandas()  # CORE rows at most
    m = len(top)
    order = np.argsort(top["h"].to_numpy(np.int64))
    known = top["h"].to_numpy(np.int64)[order]
    pairs = class_pairs(slices, spark.sparkContext.broadcast((known, order)), m + 2, m, m + 1)
    fixed = np.full(m + 2, -1)
    fixed[m], fixed[m + 1] = END, RARE
    cls = exchange(pairs, fixed, CLASSES)
    g = np.zeros((KINDS, KINDS))
    np.add.at(g, (np.repeat(cls, m + 2), np.tile(cls, m + 2)), pairs.ravel())
    core = spark.sparkContext.broadcast((known, cls[:m][order]))
    own = spark.createDataFrame([(int(h), int(c), int(k)) for h, c, k in zip(top["h"], top["c"], cls[:m], strict=True)], "h long, c long, cls int")
    words = W.written(own.union(moved_words(slices, core, g)), "words")
    size, kinds = np.zeros(KINDS), np.zeros(KINDS)
    for r in words.groupBy("cls").agg(F.sum("c").alias("c"), F.count("*").alias("k")).collect():  # KINDS rows at most
        size[r["cls"]], kinds[r["cls"]] = r["c"], r["k"]
    W.dropped(counts)
    replies = answers(slices, words)
    ends = learnt_rows(slices)  # Spark holds the last job's shuffles, so this one comes before they are freed
    W.freed(spark)
    ready = answered(slices, replies)

    def fill(mine, b):
        for r in range(b.num_rows):
            seq, cls = _sequence(b, r, "cls", "u1")
            k = np.append(cls, END).astype(np.int64)[seq]
            mine += np.bincount(k[:-1] * KINDS + k[1:], minlength=KINDS * KINDS)

    g = W.summed_sketch(ready, KINDS * KINDS, fill, text="low").reshape(KINDS, KINDS)
    prior = (g.sum(0) + 0.5) / (g.sum() + 0.5 * KINDS)
    trans = (g + STRENGTH * prior) / (g.sum(1, keepdims=True) + STRENGTH)
    size[END], kinds[END] = ends, 1
    return ClassModel(words, trans, size, kinds, int(s[0]) + ends, int(s[1]) + (ends > 0)), ready


def learnt_rows(slices: DataFrame) -> int:
    """How many rows are learnt from."""

    def fill(mine, b):
        mine[0] += sum(int(_unpacked(b, "learn", r, "?").sum()) for r in range(b.num_rows))

    return int(W.summed_sketch(slices.select("learn"), 1, fill, text="learn")[0])


def score(ready: DataFrame, model: ClassModel) -> DataFrame:
    """(doc_id, n_tokens, n_known, base_score, score) of each row coded in ``ready``; a null text is one end token."""
    m = (model.trans, model.size, model.kinds, model.n + model.v + 1)
    held = ready.sparkSession.sparkContext.broadcast(m)

    def run(batches):
        trans, size, kinds, base_d = held.value
        for b in batches:
            for r in range(b.num_rows):
                starts, codes = _unpacked(b, "starts", r, "<i8"), _codes(b, r)
                k, n = len(starts) - 1, len(codes)
                cls_of = _unpacked(b, "cls", r, "u1")
                raw = _unpacked(b, "c", r, "u1")
                c_of = raw.view("<u4" if len(raw) == 4 * len(cls_of) else "<i8").astype(np.int64)
                seq, count = np.full(n + k + 1, END), np.full(n + k + 1, size[END])
                rows = np.repeat(np.arange(k), np.diff(starts))
                at = np.arange(n) + rows + 1
                seq[at], count[at] = cls_of[codes], c_of[codes]
                cl, count = seq[1:], count[1:]
                # rare words: add-one inside their class, with one place for the unknown word
                emit = np.where(cl == RARE, (count + 1) / (size[RARE] + kinds[RARE] + 1), count / np.maximum(size[cl], 1))
                plain = (count + 1) / base_d
                logs = np.log10(LAMBDA * trans[seq[:-1], cl] * emit + (1 - LAMBDA) * plain)
                begin = starts[:-1] + np.arange(k)
                known = np.bincount(rows, c_of[codes] > 0, k).astype(np.int64) + (size[END] > 0)
                yield pa.record_batch({
                    "doc_id": b.column(b.schema.get_field_index("ids"))[r].values, "n_tokens": pa.array(np.diff(starts) + 1), "n_known": pa.array(known),
                    "base_score": pa.array(np.add.reduceat(np.log10(plain), begin)), "score": pa.array(np.add.reduceat(logs, begin)),
                })

    kind = ready.schema["ids"].dataType.elementType.simpleString()
    return ready.mapInArrow(run, f"doc_id {kind}, n_tokens long, n_known long, base_score double, score double")


def score_documents(documents: DataFrame, model: ClassModel) -> DataFrame:
    """score() of rows of (doc_id, text) that the model was not made with."""
    slices = W.written(coded(documents, F.lit(False)), "coded")
    return score(answered(slices, answers(slices, model.words)), model)


def perplexity(scores: DataFrame) -> DataFrame:
    """One row: tokens, base_perplexity, perplexity of all rows of ``scores``."""
    t = F.sum("n_tokens")
    return scores.agg(t.alias("n_tokens"), F.pow(F.lit(10.0), -F.sum("base_score") / t).alias("base_perplexity"), F.pow(F.lit(10.0), -F.sum("score") / t).alias("perplexity"))


def op3_class_lm(spark, sf_dir) -> DataFrame:
    documents = W.docs(spark, sf_dir).select("doc_id", "text")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 7 == 2, F.lit(False))
    model, ready = train(documents, ~held)
    out = score(ready, model)
    return out.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", F.lit(model.n).cast("long").alias("train_tokens"), "base_score", "score")
