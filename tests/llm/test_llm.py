"""Brute-force twins and awkward rows for the text operators."""

import hashlib
import random
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from driftrank.llm import class_lm, decontaminate, fingerprint, jaccard_join, licenses, pieces, substring_dedup, token_store, toxicity, url_filter
from driftrank.llm import words as W

R = random.Random(7)
VOCAB = [f"w{k}é" if k % 9 == 0 else f"Word{k}" for k in range(400)]


def text(n):
    return " ".join(R.choice(VOCAB) for _ in range(n))


BASE, SHARED = text(120), text(60)


def edited(s, k):
    w = s.split()
    for _ in range(k):
        w[R.randrange(len(w))] = R.choice(VOCAB)
    return " ".join(w)


ROWS = [(1, None), (2, ""), (3, " \t\n"), (4, "one"), (5, "Two words"), (6, "TWO words"), (7, text(3000)), (8, BASE), (9, BASE), (9, BASE), (None, BASE), (None, None)]
ROWS += [(20 + k, edited(BASE, 1 + k % 6)) for k in range(40)] + [(100 + k, f"{text(30)} {SHARED}\n{text(5 + k)}") for k in range(8)] + [(120, "a a " * 60)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "x", "s") for i, t in ROWS], "doc_id long, text string, kept string, th string").repartition(3)


def low(t):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "").encode().split()


def shingles(t, k):
    w = low(t)
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


@pytest.mark.parametrize("k,percent", [(3, 90), (5, 80)])
@pytest.mark.parametrize("chunk", [8, 1024])
def test_jaccard(docs, k, percent, chunk, monkeypatch):
    monkeypatch.setattr(jaccard_join, "CHUNK", chunk)
    got = sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_classes(docs, k, percent).collect() if r["doc_id"] is not None)
    sets = {i: shingles(t, k) for i, t in ROWS if i is not None}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                up[y] = x
    assert got == sorted((i, len(sets[i]), find(i)) for i, _ in ROWS if i is not None)


def test_substrings(docs):
    out = substring_dedup.dedup_substrings(docs)
    got = sorted(((r["doc_id"] is None, r["doc_id"] or 0, r["n_words"], r["n_removed"], r["kept_sha256"]) for r in out.collect()))
    seen = {}
    for _, t in ROWS:
        w = (t or "").encode().split()
        for p in range(len(w) - 34):
            seen[tuple(w[p : p + 35])] = seen.get(tuple(w[p : p + 35]), 0) + 1
    want = []
    for i, t in ROWS:
        w = (t or "").encode().split()
        gone = {q for p in range(len(w) - 34) if seen[tuple(w[p : p + 35])] > 1 for q in range(p, p + 35)}
        left = b" ".join(x for q, x in enumerate(w) if q not in gone)
        want.append((i is None, i or 0, len(w), len(gone), hashlib.sha256(left).hexdigest()))
    assert got == sorted(want)


def test_language_model(docs, monkeypatch):
    """Base and class scores against plain sums over the word table; probabilities over all words and one unknown word sum to 1."""
    monkeypatch.setattr(class_lm, "CORE", 40)
    learn = "coalesce(doc_id % 7 <> 2, false)"
    model, ready = class_lm.train(docs, F.expr(learn))
    out = class_lm.score(ready, model).collect()
    train = [t for i, t in ROWS if i is not None and i % 7 != 2]
    c = {}
    for t in train:
        for w in [*low(t), b"\n"]:
            c[w] = c.get(w, 0) + 1
    n, v = sum(c.values()), len(c)
    assert (model.n, model.v) == (n, v)
    table = {r["h"]: (r["c"], r["cls"]) for r in model.words.collect()}
    words = {w: table[class_lm._hash([w.decode()])[0]] for w in c if w != b"\n"}
    assert len(words) == len(table) and all(words[w][0] == c[w] for w in words)
    assert all((k == class_lm.RARE) == (x < class_lm.LEAST) for x, k in words.values()) and len({k for _, k in words.values()}) > 5
    size, kinds, pairs = np.zeros(class_lm.KINDS), np.zeros(class_lm.KINDS), np.zeros((class_lm.KINDS,) * 2)
    for x, k in words.values():
        size[k], kinds[k] = size[k] + x, kinds[k] + 1
    size[0], kinds[0] = c[b"\n"], 1

    def classes(t):
        return [0, *(words.get(w, (0, class_lm.RARE))[1] for w in low(t)), 0]

    for t in train:
        k = classes(t)
        for a, b in zip(k, k[1:]):
            pairs[a, b] += 1
    prior = (pairs.sum(0) + 0.5) / (pairs.sum() + 0.5 * class_lm.KINDS)
    trans = (pairs + class_lm.STRENGTH * prior) / (pairs.sum(1, keepdims=True) + class_lm.STRENGTH)
    assert np.allclose(trans, model.trans) and np.allclose(size, model.size)

    def emit(w, k):
        return (c.get(w, 0) + 1) / (size[1] + kinds[1] + 1) if k == 1 else c[w] / size[k]

    def p(w, k, before):
        return class_lm.LAMBDA * trans[before, k] * emit(w, k) + (1 - class_lm.LAMBDA) * (c.get(w, 0) + 1) / (n + v + 1)

    want = []
    for i, t in ROWS:
        k, w = classes(t), [*low(t), b"\n"]
        base = sum(np.log10((c.get(x, 0) + 1) / (n + v + 1)) for x in w)
        want.append((i or -1, len(w), sum(x in c for x in w), round(base, 4), round(sum(np.log10(p(x, b, a)) for x, a, b in zip(w, k, k[1:])), 4)))
    got = sorted((r["doc_id"] or -1, r["n_tokens"], r["n_known"], round(r["base_score"], 4), round(r["score"], 4)) for r in out)
    assert [g[:3] for g in got] == [x[:3] for x in sorted(want)]
    assert np.allclose([g[3:] for g in got], [x[3:] for x in sorted(want)], atol=2e-4)
    for before in range(class_lm.KINDS):
        if kinds[before]:
            missing = trans[before][kinds == 0].sum()  # classes without words keep some mass
            total = sum(p(w, k, before) for w, (_, k) in words.items()) + p(b"\n", 0, before) + p(b"never seen", 1, before)
            assert total == pytest.approx(1 - class_lm.LAMBDA * (missing if kinds[1] else missing - trans[before][1]), abs=1e-9)
    again = class_lm.score_documents(docs, model).collect()
    assert sorted(r["score"] for r in again) == pytest.approx(sorted(r["score"] for r in out))
    empty, ready = class_lm.train(docs.limit(0))
    assert empty.n == 0 and class_lm.score(ready, empty).count() == 0


def test_tokens_round_trip(docs, tmp_path):
    from tokenizers import Tokenizer

    folder = f"{W.shared(docs.sparkSession)}/t-{tmp_path.name}-{uuid.uuid4().hex}"
    token_store.write_tokens(docs, folder)
    got = token_store.read_tokens(docs.sparkSession, folder).orderBy("start").collect()
    tok = Tokenizer.from_file(W.tokenizer_path("word_bpe_49k.json"))
    want = sorted(tok.encode(t or "", add_special_tokens=False).ids + [2] for _, t in ROWS)
    assert sorted(r["ids"] for r in got) == want
    assert [r["doc_id"] or -1 for r in got] == sorted(r["doc_id"] or -1 for r in got)
    at = 0
    for r in got:
        assert r["start"] == at and r["ids_crc32"] == zlib.crc32(np.array(r["ids"], "<u4").tobytes())
        at += r["n_tokens"]


def test_codec_checkpoints_and_checksum():
    codec = token_store.Codec(token_store.Codec.table(np.arange(500)))
    x = np.random.default_rng(1).integers(0, 500, 600_001)
    block = codec.encode(x)
    assert (codec.decode(block) == x).all()
    assert (codec.decode(block, 256, 5) == x[256 * 1024 : 261 * 1024]).all()
    with pytest.raises(ValueError):
        codec.decode(block[:-8] + bytes(v ^ 1 for v in block[-8:]))


def test_pieces(docs):
    got = pieces.encode_documents(docs).collect()
    assert len(got) == len(ROWS) and all(r["round_trip"] for r in got)
    sp = pieces.pieces_of(W.tokenizer_path("piece_bpe_32k.model"))
    assert sorted(round(sp.text_nbest(t or "", 1)[0][0], 3) for _, t in ROWS) == sorted(round(r["score"], 3) for r in got)
    best = sp.nbest("▁there", 50)
    every = []

    def walk(at, done):
        if not at:
            every.append(done)
        for s, p, _ in sp.into("▁there", at):
            walk(s, done + p)

    walk(6, 0.0)
    assert [x for x, _ in best] == pytest.approx(sorted(every, reverse=True)[:50])
    assert sum(np.exp(list(sp.score.values()))) == pytest.approx(1)
    assert pieces.decode_documents(pieces.encode_documents(docs)).where("text is null").count() == 0


def test_urls(spark):
    rows = [(1, "HTTP://Example.NET/en/x?q"), (2, "http://a.example.net/EN/"), (3, "http://net"), (4, None), (5, "nothing"), (6, "http://x.org/fr/#/"), (7, "https://www.example.com/de/1"), (7, "https://www.example.com/de/1"), (8, "http://sub.example.org/it/")]
    got = {r["page_id"]: r for r in url_filter.filter_urls(spark.createDataFrame(rows, "page_id long, url string")).collect()}
    assert [got[k]["rule"] for k in range(1, 9)] == ["example.net/en/", "net/", None, None, None, "org/fr/", "example.com/de/", None]
    assert (got[1]["host"], got[1]["path"], got[3]["path"], got[5]["host"]) == ("example.net", "/en/x", "", "")
    assert all(r["verdict"] in ("allow", "block") for r in got.values())
    assert url_filter.filter_urls(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_fingerprints(docs, spark):
    rows = fingerprint.fingerprints(docs).select("text", "fingerprint").collect()
    by = {}
    for r in rows:
        assert by.setdefault(r["text"] or "", r["fingerprint"]) == r["fingerprint"] and len(r["fingerprint"]) in (0, 256)
    nxt = fingerprint.with_next(docs.where("doc_id is not null").dropDuplicates(["doc_id"]), 5).collect()
    ids = dict((i, t or "") for i, t in ROWS if i is not None)
    order = sorted(ids, reverse=True)
    for r in nxt:
        k = order.index(r["doc_id"])
        assert r["next_text"] == ids[order[(k + 1) % len(order)]]
    plan = fingerprint.fingerprints(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan
    assert fingerprint.with_next(docs.limit(0), 5).count() == 0


def test_licenses(spark):
    rows = [(1, "Intro.\nReleased under the MIT License.\nMore"), (2, "Licensed under the Apache License, Version 2.0 (the \"License\");\nyou may not use this file except in compliance with the License. You may obtain a copy of the License at\nx"), (3, None), (4, ""), (5, "LICENSED under CC BY-NC 4.0.  Licensed under the Apache License, Version 2.0.")]
    got = {r["doc_id"]: r for r in licenses.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [sorted(got[k]["licenses"]) for k in range(1, 6)] == [["MIT"], ["Apache-2.0"], [], [], ["Apache-2.0", "CC-BY-NC-4.0"]]
    assert got[2]["sentence_ids"].split() == ["apache-2", "apache-comply", "apache-copy"] and got[5]["permissive"] is False and got[3]["permissive"] is None


def test_leaks(spark):
    item = text(24)
    rows = [(1, f"{text(50)} {item.upper()}, {text(9)}"), (2, f"{text(20)} {edited(item, 1)}"), (3, text(200)), (4, None), (5, item), (5, item)]
    bench = spark.createDataFrame([(7, item), (8, None), (9, "")], "item_id long, text string")
    got = [(r["doc_id"], r["item_id"], r["start_word"]) for r in decontaminate.find_leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()]
    assert {(1, 7, 50), (5, 7, 0)} <= set(got) and {i for i, _, _ in got} <= {1, 2, 5}
    assert decontaminate.find_leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench.limit(0)).count() == 0


def test_toxicity_learns_stems_and_handles_odd_rows(spark):
    rng = random.Random(2)
    clean = ["".join(rng.choice("abcdeghik") for _ in range(rng.randint(2, 7))) for _ in range(300)]
    made, marks = [], []
    for k in range(500):
        w = [rng.choice(clean) for _ in range(rng.randint(5, 60))]
        if k % 3 == 0:
            w[rng.randrange(len(w))] = "vloot" + rng.choice(["", "ur", "ing", "s"])
        made.append(" ".join(w))
        marks.append(int(k % 3 == 0))
    m = toxicity.fit(made[:400], marks[:400])
    s = m.scores(pa.array(made[400:]))
    y = np.array(marks[400:])
    assert s[y == 1].min() > np.median(s[y == 0])
    odd = m.scores(pa.array([None, "", "  ", "x", "vloot " * 30_000]))
    assert ((odd >= 0) & (odd <= 1)).all()
    assert toxicity.fit(["a"], [1]).scores(pa.array(["b", None])).shape == (2,)
    frame = toxicity.score(spark.createDataFrame([(1, "x", 1.0), (None, None, None)], "doc_id long, text string, c0 double"), m)
    assert frame.columns == ["doc_id", "text", "c0", "toxic_score"] and frame.count() == 2


def test_components_of_paths_stars_and_nothing(spark):
    from driftrank.llm.components import components

    rng = np.random.default_rng(3)
    path = [(i + 1, i) for i in range(1000, 1300)] + [(7000 - i, 7001 - i) for i in range(300)]
    edges = path + [(5, k) for k in range(20, 60)] + [tuple(map(int, p)) for p in rng.integers(10_000, 10_400, (260, 2))] + [(9, 9), (5, 20)]
    up = {}

    def find(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        if a != b:
            a, b = find(a), find(b)
            up[max(a, b)] = min(a, b)
    got = components(spark.createDataFrame(edges, "a long, b long").repartition(9))
    assert {r["node"]: r["component"] for r in got.collect()} == {x: find(x) for x in up}
    assert got.count() == len(up)
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
