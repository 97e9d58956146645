"""Toxicity: subword-bag embeddings averaged into a linear softmax, trained jointly in numpy.

A word's vector is the sum over its boundary-marked character n-grams (hashed into ``BUCKETS`` rows), so misspellings
share most of theirs. Long texts are read as passages of ``SPAN`` words; each passage is averaged and classified, and
a text scores as its most toxic passage. Training alternates: every passage of a toxic text starts with the text's
label, then only its most toxic one keeps it (the text's label says nothing about the others).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftrank.llm import words as W

BUCKETS, DIM, SPAN = 1 << 17, 4, 3
GAIN, DECAY, LEAST = 20.0, 1e-5, 0.005  # scale of averages, weight decay, share of the texts an n-gram must be in
GRAMS = (4, 5)
SAMPLE = 2500  # most labelled rows of each class that the classifier is fitted on


def word_grams(vocab: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Bucket ids of all character n-grams of all words, and where each word's begin."""
    marked = np.frombuffer(("".join(f"<{w}>" for w in vocab)).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    size = np.array([len(w) + 2 for w in vocab], np.int64)
    ends = np.cumsum(size)
    left = np.repeat(ends, size) - np.arange(len(marked))
    own = np.repeat(np.arange(len(vocab)), size)
    ids, who = [], []
    for n in GRAMS:
        h = W.mix(W.rolling(W.mix(marked + np.uint64(1)), n) + np.uint64(n))
        ok = left[: len(h)] >= n
        ids.append((h[ok] % np.uint64(BUCKETS)).astype(np.int64))
        who.append(own[: len(h)][ok])
    ids, who = np.concatenate(ids), np.concatenate(who)
    by = np.argsort(who, kind="stable")
    return ids[by], np.searchsorted(who[by], np.arange(len(vocab) + 1))


def _word_sums(table: np.ndarray, ids: np.ndarray, cut: np.ndarray) -> np.ndarray:
    """Mean of the rows of each word's n-grams; words without any (none: '<', '>' and one character make three) are 0."""
    total = np.concatenate((np.zeros((1, *table.shape[1:])), np.cumsum(table[ids], axis=0, dtype=np.float64)))
    return (total[cut[1:]] - total[cut[:-1]]) / np.maximum(np.diff(cut), 1).reshape(-1, *[1] * (table.ndim - 1))


def spans(starts: np.ndarray) -> np.ndarray:
    """Offsets of passages: each row is cut into pieces of SPAN words, overlapping by none."""
    n = np.diff(starts)
    k = np.maximum(1, -(-n // SPAN))
    first = np.repeat(starts[:-1], k)
    inner = np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)
    return first + inner * SPAN


def clean(texts: pa.Array) -> W.Words:
    import pyarrow.compute as pc

    low = pc.utf8_lower(pc.fill_null(texts, "").cast(pa.large_string()))
    return W.Words(pc.replace_substring_regex(low, r"[\pP\pS]+", " "))


class Model:
    """``bucket`` has each n-gram's contribution to the logit: the output layer applied to its embedding."""

    def __init__(self, bucket: np.ndarray, bias: float):
        self.bucket, self.bias = bucket, bias

    def scores(self, texts: pa.Array) -> np.ndarray:
        w = clean(texts)
        prior = 1 / (1 + np.exp(-self.bias))
        out = np.full(len(w.starts) - 1, min(prior, 0.5))
        if not w.n:
            return out
        ids, cut = word_grams(w.vocab)
        word = _word_sums(self.bucket, ids, cut)[w.codes]
        at = spans(w.starts)
        full = np.diff(w.starts) > 0
        k = np.maximum(1, -(-np.diff(w.starts) // SPAN))
        begin = np.concatenate(([0], np.cumsum(k)))
        end = np.minimum(at + SPAN, np.repeat(w.starts[1:], k))
        total = np.concatenate(([0.0], np.cumsum(word)))
        z = (total[end] - total[np.minimum(at, end)]) / np.maximum(end - at, 1) + self.bias
        top = np.maximum.reduceat(z, begin[:-1])
        out[full] = 1 / (1 + np.exp(-np.clip(top[full], -30, 30)))
        return out


class Bags:
    """N-gram bags of passages, averages over words and their known n-grams, made batch by batch from the word codes."""

    def __init__(self, w: W.Words, at: np.ndarray, end: np.ndarray, ids: np.ndarray, cut: np.ndarray, known: np.ndarray):
        self.codes, self.at, self.size = w.codes, at, end - at
        keep = known[ids]
        self.all = np.maximum(np.diff(cut), 1)  # n-grams of a word, the unknown ones too
        self.ids, self.cut = ids[keep], np.concatenate(([0], np.cumsum(keep)))[cut]

    def take(self, rows: np.ndarray) -> tuple[np.ndarray, ...]:
        """Of some passages: passage, word and weight of each entry; n-gram, word and weight of each word's known n-grams."""
        n = self.size[rows]
        codes = self.codes[np.repeat(self.at[rows], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]
        words, inv = np.unique(codes, return_inverse=True)
        k = self.cut[words + 1] - self.cut[words]
        grams = self.ids[np.repeat(self.cut[words], k) + np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)]
        return np.repeat(np.arange(len(rows)), n), inv, np.repeat(1 / np.maximum(n, 1), n), grams, np.repeat(np.arange(len(words)), k), np.repeat(1 / self.all[words], k)


def _epoch(state: dict, bags: Bags, use: np.ndarray, target: np.ndarray, rng: np.random.Generator, rate: float) -> None:
    """One shuffled pass of Adagrad over the embeddings and the softmax together; both classes weigh the same."""
    share = target[use].mean()
    weight = np.where(target == 1, 0.5 / max(share, 1e-9), 0.5 / max(1 - share, 1e-9))
    for rows in np.array_split(rng.permutation(use), max(1, len(use) // 256)):
        who, word, part, grams, of, gram_part = bags.take(rows)
        emb, out = state["emb"], state["out"]
        words = int(word.max()) + 1 if len(word) else 0
        vec = np.stack([np.bincount(of, gram_part * emb[grams, k], words) for k in range(DIM)], 1)
        bag = np.stack([np.bincount(who, part * vec[word, k], len(rows)) for k in range(DIM)], 1) * GAIN
        z = bag @ out + state["bias"]
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        t = target[rows]
        d = (p - np.stack((1 - t, t), 1)) * weight[rows][:, None] / len(rows)
        back = (d @ out.T) * GAIN
        ub, inv = np.unique(grams, return_inverse=True)
        vec = np.stack([np.bincount(word, part * back[who, k], words) for k in range(DIM)], 1)
        grad = np.stack([np.bincount(inv, gram_part * vec[of, k], len(ub)) for k in range(DIM)], 1) + DECAY * emb[ub]
        for name, at, g in (("emb", ub, grad), ("out", slice(None), bag.T @ d), ("bias", slice(None), d.sum(axis=0))):
            state["g_" + name][at] += g**2
            state[name][at] -= rate * g / np.sqrt(state["g_" + name][at])


def fit(texts: list[str], labels: list[int], seed: int = 5, whole: int = 3, parts: int = 4, rate: float = 0.1) -> Model:
    """Joint training of the n-gram embeddings and the two-class softmax.

    ``whole`` epochs on averages of whole texts, then ``parts`` epochs on passages: all of the clean texts', and of each
    toxic text the one that scores highest so far. N-grams in less than LEAST of the texts (or in fewer than 3) stay out.
    """
    y = np.array(labels, np.float64)
    if not len(y) or y.min() == y.max():
        base = (y.sum() + 1) / (len(y) + 2)
        return Model(np.zeros(BUCKETS), float(np.log(base / (1 - base))))
    rng = np.random.default_rng(seed)
    w = clean(pa.array(texts, pa.large_string()))
    ids, cut = word_grams(w.vocab)
    seen = np.zeros(BUCKETS, np.int64)
    for s, e in zip(w.starts[:-1].tolist(), w.starts[1:].tolist(), strict=True):
        codes = np.unique(w.codes[s:e])
        grams = cut[codes + 1] - cut[codes]
        seen[np.unique(ids[np.repeat(cut[codes], grams) + np.arange(grams.sum()) - np.repeat(np.cumsum(grams) - grams, grams)])] += 1
    known = seen >= max(3, int(LEAST * len(y)))
    state = {"emb": rng.normal(0, 0.02, (BUCKETS, DIM)) * known[:, None], "out": rng.normal(0, 0.3, (DIM, 2)), "bias": np.zeros(2)}
    state |= {"g_emb": np.full((BUCKETS, DIM), 1e-6), "g_out": np.full((DIM, 2), 1e-2), "g_bias": np.full(2, 1e-2)}
    bags = Bags(w, w.starts[:-1], w.starts[1:], ids, cut, known)
    for _ in range(whole):
        _epoch(state, bags, np.flatnonzero(np.diff(w.starts) > 0), y, rng, rate)
    k = np.maximum(1, -(-np.diff(w.starts) // SPAN))
    begin = np.concatenate(([0], np.cumsum(k)))
    at = spans(w.starts)
    end = np.minimum(at + SPAN, np.repeat(w.starts[1:], k))
    row = np.repeat(np.arange(len(y)), k)
    bags, some = Bags(w, at, end, ids, cut, known), end > at
    for _ in range(parts):
        bucket = state["emb"] @ (state["out"][:, 1] - state["out"][:, 0]) * GAIN
        total = np.concatenate(([0.0], np.cumsum(_word_sums(bucket * known, ids, cut)[w.codes])))
        z = (total[end] - total[at]) / np.maximum(end - at, 1)
        best = np.maximum.reduceat(z, begin[:-1])[row]
        _epoch(state, bags, np.flatnonzero(some & ((y[row] == 0) | (z >= best - 1e-9))), y[row], rng, rate)
    bucket = state["emb"] @ (state["out"][:, 1] - state["out"][:, 0]) * GAIN
    model = Model(bucket * known, float(state["bias"][1] - state["bias"][0]))
    del w, bags, ids, cut, total, z, best, some, at, end, row, k, begin  # the words of all texts are made once more
    W.trim()
    return calibrated(model, texts, y)


def calibrated(model: Model, texts: list[str], y: np.ndarray) -> Model:
    """Shift the bias so that 0.7 is where the fitted rows are told apart best, between the classes if they part."""
    p = np.clip(model.scores(pa.array(texts, pa.large_string())), 1e-12, 1 - 1e-12)
    z = np.log(p / (1 - p))
    by = np.argsort(-z)
    t = y[by]
    tp, fp = np.cumsum(t), np.cumsum(1 - t)
    gain = tp / max(1, t.sum()) - 20 * fp / max(1, (1 - t).sum())
    at = int(np.argmax(gain))
    cut = (z[by][at] + z[by][min(at + 1, len(z) - 1)]) / 2
    return Model(model.bucket, model.bias - cut + float(np.log(0.7 / 0.3)))


def train(documents: DataFrame, labels: DataFrame, learn) -> Model:
    """Fit on the whole texts of at most SAMPLE labelled rows of each class (by hash order of doc_id).

    ``learn``: condition on doc_id of the rows that may be learnt from. Null texts, ids and labels are left out;
    of a doc_id with several texts, the least one is learnt from.
    """
    tags = labels.where("doc_id is not null and toxic in (0, 1)").where(learn).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    tags = tags.withColumn("h", F.xxhash64("doc_id"))
    picked = tags.where("toxic = 1").orderBy("h").limit(SAMPLE).union(tags.where("toxic = 0").orderBy("h").limit(SAMPLE))
    picked = W.written(picked, "labelled")
    rows = documents.where("text is not null").select("doc_id", "text").join(F.broadcast(picked), "doc_id")

    def run(batches):
        # one task for the whole sample, of a documented size, so that the driver holds the fitted table alone
        got = [b.to_pandas() for b in batches]
        got = pd.concat(got).sort_values("doc_id") if got else pd.DataFrame({"text": [], "toxic": []})
        m = fit(got["text"].tolist(), got["toxic"].tolist())
        del got
        W.trim()
        yield pa.record_batch({"bucket": pa.array([m.bucket.astype("<f4").tobytes()], pa.binary()), "bias": pa.array([m.bias], pa.float64())})

    one_each = rows.groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))
    r = one_each.repartition(1).mapInArrow(run, "bucket binary, bias double").first()
    return Model(np.frombuffer(bytes(r["bucket"]), "<f4").astype(np.float64), r["bias"]) if r else fit([], [])


def held_out():
    """The rows that may not be learnt from; a row without an id is not one of them (nor has it a label)."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False)).alias("held_out")


def score(documents: DataFrame, model: Model) -> DataFrame:
    """All columns of ``documents`` with toxic_score; null or empty texts score the prior, at most 0.5.

    Repeated rows repeat their score, an empty table stays empty. A column named toxic_score is replaced.
    """
    documents = documents.drop("toxic_score")
    held = documents.sparkSession.sparkContext.broadcast((model.bucket.astype(np.float32), model.bias))
    names = documents.columns

    def run(batches):
        m = Model(held.value[0].astype(np.float64), held.value[1])
        for b in W.slices(batches, f"c{names.index('text')}"):
            s = m.scores(b.column(names.index("text")))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s, pa.float64())], [*b.schema.names, "toxic_score"])

    plain = documents.toDF(*(f"c{i}" for i in range(len(names))))
    schema = ", ".join(f"c{i} {f.dataType.simpleString()}" for i, f in enumerate(documents.schema.fields))
    return plain.mapInArrow(run, f"{schema}, toxic_score double").toDF(*names, "toxic_score")


def op1_toxicity(spark, sf_dir) -> DataFrame:
    documents = W.docs(spark, sf_dir).select("doc_id", "text")
    learn = F.crc32(F.col("doc_id").cast("string")) % 3 != 1
    model = train(documents, W.docs(spark, sf_dir, "labels"), learn)
    out = score(documents, model)
    return out.select("doc_id", held_out(), F.col("toxic_score").alias("score"), (F.col("toxic_score") >= 0.7).cast("int").alias("predicted"))
