"""SentencePiece encoding and decoding by N-best segmentation over the piece lattice.

A forward Viterbi pass gives the best score of every prefix; these scores are exact heuristics for an A-star search
that runs backward from the end, so complete paths leave its queue in order of score. Scores are log-probabilities of
pieces. A model that holds them is used as it is. A model of merge ranks (whole numbers, as pair merging leaves them)
has no probabilities, and none are trained here: its pieces get those of the harmonic law, 1 / rank over the sum of all,
in the order of their merges; pieces without a merge (marks alone, in runs too) come last. So segmentations are the
likeliest under that law, mostly but not always those of the library's greedy merging; decoding equals the library's.
No piece holds a space mark after another character, so a text's lattice is a chain of the lattices of its words, each
with the run of marks before it: bulk encoding runs the forward pass over all distinct words of a slice at once, and a
text's second path differs from its best one in the one word that loses least, where the A-star search finds it.
"""

from __future__ import annotations

import heapq
import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from driftrank.llm import words as W

MARK = "▁"
_BASE = np.uint64(0x9E3779B97F4A7C15)
WIDTHS = (8, 16, 32, 64)
BLOCK = 16_000


class Pieces:
    """The pieces and scores of a model file."""

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        text = [sp.id_to_piece(i) for i in range(n)]
        self.byte = {int(t[3:5], 16): i for i, t in enumerate(text) if sp.is_byte(i)}
        usable = [i for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        if any(MARK in text[i].lstrip(MARK) for i in usable):
            raise ValueError("a piece goes on after a word")
        score = {i: sp.get_score(i) for i in usable}
        if all(x == int(x) for x in score.values()):
            share = 1 / (1 + np.arange(len(usable)))
            by_rank = sorted(usable, key=lambda i: (-score[i], i))
            score = dict(zip(by_rank, np.log(share / share.sum()).tolist(), strict=True))
        self.score = {text[i]: score[i] for i in usable}
        self.id = {text[i]: i for i in usable}
        self.unknown = min(self.score.values()) - 10.0
        self.longest = max(map(len, self.id))
        self.width = np.uint16 if n <= 1 << 16 else np.uint32
        self.raw = np.array([bytes([int(t[3:5], 16)]) if sp.is_byte(i) else b"" if sp.is_control(i) else t.replace(MARK, " ").encode() for i, t in enumerate(text)], object)
        keys = [(self._hash(t), i) for t, i in self.id.items()]
        keys.sort()
        self.keys = np.array([k for k, _ in keys], np.uint64)
        self.ids = np.array([i for _, i in keys], np.int32)
        self.points = np.array([self.score[text[i]] for _, i in keys])
        self.maybe = np.zeros(1 << 22, bool)
        self.maybe[(W.mix(self.keys) >> np.uint64(42)).astype(np.int64)] = True
        self.kept: dict[tuple[str, int], list] = {}

    @staticmethod
    def _hash(t: str) -> int:
        h = 0
        for c in t:
            h = (h * int(_BASE) + ord(c) + 1) & 0xFFFFFFFFFFFFFFFF
        return h

    def into(self, word: str, e: int) -> list[tuple[int, float, tuple[int, ...]]]:
        """(start, score, ids) of the pieces of a word that end at ``e``; unknown characters become bytes."""
        out = []
        for s in range(max(0, e - self.longest), e):
            t = word[s:e]
            if t in self.id:
                out.append((s, self.score[t], (self.id[t],)))
            elif e == s + 1:
                out.append((s, self.unknown, tuple(self.byte[b] for b in t.encode())))
        return out

    def nbest(self, word: str, n: int) -> list[tuple[float, list[int]]]:
        """The n best (score, ids) of a word (spaces as marks), best first; fewer if there are fewer.

        Arcs are looked up where they are needed and not kept, so a very long word costs one number a character.
        """
        best = [0.0] + [-np.inf] * len(word)
        for e in range(1, len(word) + 1):
            best[e] = max((best[s] + p for s, p, _ in self.into(word, e)), default=-np.inf)
        queue, tick, out = [(-best[-1], 0, len(word), 0.0, None)], 0, []
        while queue and len(out) < n:
            _, _, at, done, path = heapq.heappop(queue)
            if not at:
                ids: list[int] = []
                while path:
                    ids.extend(path[0])
                    path = path[1]
                out.append((done, ids))
                continue
            for s, p, ids in self.into(word, at):
                tick += 1
                heapq.heappush(queue, (-(best[s] + p + done), tick, s, done + p, (ids, path)))
        return out

    def second(self, word: str) -> list:
        key = (word, 2)
        if key not in self.kept:
            if len(self.kept) > 100_000:
                self.kept.clear()
            self.kept[key] = self.nbest(word, 2)
        return self.kept[key]

    def text_nbest(self, text: str, n: int) -> list[tuple[float, list[int]]]:
        """The n best segmentations of a whole text: word lists are joined best-first, so the order is exact."""
        if not text:
            return [(0.0, [])]
        lists = [self.nbest(w, n) for w in split(text)]
        out = [(0.0, [])]
        for ls in lists:
            out = heapq.nlargest(n, ((a + b, x + y) for a, x in out for b, y in ls), key=lambda t: t[0])
        return out

    def decode(self, ids: np.ndarray) -> str:
        body = b"".join(self.raw[ids].tolist())
        return (body[1:] if body[:1] == b" " else body).decode("utf-8", "replace")

    def _find(self, h: np.ndarray) -> np.ndarray:
        """Index of each hash among the pieces, or -1."""
        out = np.full(h.shape, -1, np.int32)
        at = self.maybe[(W.mix(h) >> np.uint64(42)).astype(np.int64)]
        some = h[at]
        k = np.minimum(np.searchsorted(self.keys, some), len(self.keys) - 1)
        out[at] = np.where(self.keys[k] == some, k, -1)
        return out

    def bulk(self, vocab: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """For many words: all ids one after another, ids per word, best score, and how much the second path loses."""
        n = len(vocab)
        size = np.fromiter(map(len, vocab), np.int64, n)
        score, loss = np.zeros(n), np.full(n, np.inf)
        parts: list = [None] * n
        slow = size > WIDTHS[-1]
        low = 0
        for wide in WIDTHS:
            todo = np.flatnonzero((size > low) & (size <= wide))
            low = wide
            for b in range(0, len(todo), BLOCK):
                odd = self._block([vocab[i] for i in todo[b : b + BLOCK]], todo[b : b + BLOCK], size, wide, parts, score, loss)
                slow[odd] = True
        for i in np.flatnonzero(slow).tolist():
            two = self.nbest(vocab[i], 2)
            score[i], parts[i] = two[0][0], np.array(two[0][1], self.width)
            loss[i] = two[0][0] - two[1][0] if len(two) > 1 else np.inf
        count = np.fromiter(map(len, parts), np.int64, n)
        return (np.concatenate(parts) if n else np.zeros(0, self.width)), count, score, loss

    def _block(self, words, at, size, wide, parts, score, loss) -> np.ndarray:
        n = len(words)
        x = np.frombuffer("".join(w.ljust(wide, "\0") for w in words).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(n, wide).astype(np.uint64)
        long = size[at]
        inside = np.arange(wide) < long[:, None]
        h = np.zeros((n, wide), np.uint64)
        one = np.full((n, wide + 1), -np.inf)
        two, back, ids = one.copy(), np.zeros((n, wide + 1), np.int8), []
        one[:, 0] = 0
        points = []
        for k in range(1, min(self.longest, wide) + 1):
            m = wide - k + 1
            h = h[:, :m] * _BASE + x[:, k - 1 :] + np.uint64(1)
            f = self._find(np.where(inside[:, k - 1 :], h, np.uint64(0)))
            p = np.where(f >= 0, self.points[f], -np.inf)
            i = np.where(f >= 0, self.ids[f], -1)
            if k == 1:
                raw = (f < 0) & inside
                odd = (raw & (x >= 128)).any(axis=1)
                p = np.where(raw, self.unknown, p)
                i = np.where(raw, self.byte[0] + x.astype(np.int64), i)
            points.append(p)
            ids.append(i)
        for e in range(1, wide + 1):
            for k in range(1, min(self.longest, e) + 1):
                p = points[k - 1][:, e - k]
                c, d = one[:, e - k] + p, two[:, e - k] + p
                a = one[:, e]
                two[:, e] = np.maximum(np.minimum(a, c), np.maximum(two[:, e], d))
                back[:, e] = np.where(c > a, k, back[:, e])
                one[:, e] = np.maximum(a, c)
        rows = np.arange(n)
        score[at], second = one[rows, long], two[rows, long]
        loss[at] = np.where(np.isfinite(second), score[at] - second, np.inf)
        cols, pos = [], long.copy()
        grid = np.stack([np.pad(i, ((0, 0), (0, wide - i.shape[1])), constant_values=-1) for i in ids])
        while (pos > 0).any():
            k = back[rows, pos].astype(np.int64)
            cols.append(np.where(pos > 0, grid[np.maximum(k - 1, 0), rows, np.maximum(pos - k, 0)], -1))
            pos = np.maximum(pos - k, 0)
        path = np.stack(cols[::-1], 1)
        keep = path >= 0
        flat, cut = path[keep].astype(self.width), np.cumsum(keep.sum(axis=1))
        for i, part in zip(at.tolist(), np.split(flat, cut[:-1]), strict=True):
            parts[i] = part
        return at[odd]


def split(text: str) -> list[str]:
    """Words with the run of marks before each; marks at the end are a word of their own."""
    return re.findall(f"{MARK}+[^{MARK}]*|[^{MARK}]+", MARK + text.replace(" ", MARK))


def split_column(texts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """split() of a column: distinct words, the words as numbers, and the offsets of the rows, for texts without marks."""
    lists = pc.split_pattern(texts, " ")
    offs = (lists.offsets.to_numpy() - lists.offsets[0].as_py()).astype(np.int64)
    coded = pc.dictionary_encode(lists.flatten())
    vocab, codes = W.strings(coded.dictionary), coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    # a word of no characters is one mark more for the word after it, in the same row
    empty = codes == (vocab.index("") if "" in vocab else -1)
    last = np.zeros(len(codes), bool)
    last[offs[1:][np.diff(offs) > 0] - 1] = True
    kept = np.flatnonzero(~empty | last)
    before = np.diff(kept, prepend=-1)  # marks: one and those of the words of no characters before it
    offs = np.searchsorted(kept, offs)
    key, codes = np.unique(codes[kept] * (1 << 32) + before, return_inverse=True)
    return [MARK * (k & 0xFFFFFFFF) + vocab[k >> 32] for k in key.tolist()], codes.reshape(-1), offs


_open: dict[str, Pieces] = {}


def pieces_of(path: str) -> Pieces:
    if path not in _open:
        _open[path] = Pieces(path)
    return _open[path]


def encode_documents(frame: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, n_pieces, ids, score, second_score, second_crc32, ids_crc32, round_trip) for each row of (doc_id, text).

    ``ids``: the best segmentation, packed little-endian (16 bits an id for models of up to 65,536 pieces). The second
    best has its score and the crc32 of its ids in 32 bits; both are null where there is only one. Null and empty texts
    have no pieces, score 0. ``round_trip``: decoding the ids gives the text back.
    """
    path = W.tokenizer_path("piece_bpe_32k.model", path)

    def run(batches):
        sp = pieces_of(path)
        for b in W.slices(batches, limit=2 * W.SLICE_BYTES):
            texts = pc.fill_null(b.column(1), "").cast(pa.large_string())
            full = pc.greater(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
            vocab, codes, offs = split_column(texts)
            flat, count, score, loss = sp.bulk(vocab)
            begin = np.cumsum(count) - count
            cols = {c: [] for c in ("n_pieces", "ids", "score", "second_score", "second_crc32", "ids_crc32", "round_trip")}
            for r, (text, s, e) in enumerate(zip(W.strings(texts), offs[:-1].tolist(), offs[1:].tolist(), strict=True)):
                c = codes[s:e] if full[r] else codes[:0]
                n = count[c]
                ids = flat[np.repeat(begin[c] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                best = float(score[c].sum())
                cols["n_pieces"].append(len(ids))
                cols["ids"].append(ids.tobytes())
                cols["score"].append(best)
                cols["ids_crc32"].append(zlib.crc32(ids.astype("<u4").tobytes()))
                cols["round_trip"].append(sp.decode(ids) == text)
                k = int(np.argmin(loss[c])) if len(c) else -1
                if k >= 0 and np.isfinite(loss[c[k]]):
                    a = int(n[:k].sum())
                    own = ids[a : a + int(n[k])].tolist()
                    # with ties the search may find the bulk path second: the other one it found is the alternative
                    other = np.array(next(x for _, x in sp.second(vocab[c[k]]) if x != own), sp.width)
                    alt = np.concatenate((ids[:a], other, ids[a + int(n[k]) :]))
                    cols["second_score"].append(best - float(loss[c[k]]))
                    cols["second_crc32"].append(zlib.crc32(alt.astype("<u4").tobytes()))
                else:
                    cols["second_score"].append(None)
                    cols["second_crc32"].append(None)
            kinds = {"n_pieces": pa.int64(), "ids": pa.binary(), "score": pa.float64(), "second_score": pa.float64(), "second_crc32": pa.int64(), "ids_crc32": pa.int64(), "round_trip": pa.bool_()}
            yield pa.record_batch({"doc_id": b.column(0), **{c: pa.array(v, kinds[c]) for c, v in cols.items()}})

    kind = frame.schema["doc_id"].dataType.simpleString()
    return frame.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_pieces long, ids binary, score double, second_score double, second_crc32 long, ids_crc32 long, round_trip boolean")


def decode_documents(frame: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids) as encode_documents packs them; null ids give a null text."""
    path = W.tokenizer_path("piece_bpe_32k.model", path)

    def run(batches):
        sp = pieces_of(path)
        for b in batches:
            texts = [None if i is None else sp.decode(np.frombuffer(i, sp.width)) for i in b.column(1).to_pylist()]
            yield pa.record_batch({"doc_id": b.column(0), "text": pa.array(texts, pa.string())})

    kind = frame.schema["doc_id"].dataType.simpleString()
    return frame.select("doc_id", "ids").mapInArrow(run, f"doc_id {kind}, text string")


def op9_pieces(spark, sf_dir) -> DataFrame:
    return encode_documents(W.docs(spark, sf_dir)).drop("ids")
