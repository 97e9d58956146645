"""Every registered text query on one small set of tables, against brute force; the pipeline's stages on awkward rows."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest

from driftrank.llm import queries, token_store
from driftrank.llm import words as W

R = random.Random(23)
CLEAN = ["".join(R.choice("abcdeghikmnoprs") for _ in range(R.randint(2, 8))) for _ in range(3000)]


def prose(n):
    return " ".join(R.choice(CLEAN) for _ in range(n))


ITEM, PASSAGE, TWIN = prose(40), prose(55), prose(90)
DOCS, LABELS = [], []
for k in range(260):
    w = prose(R.randint(20, 60)).split()
    toxic = k % 4 == 0
    if toxic:
        for at in R.sample(range(len(w)), 4):
            w[at] = "Vloot" + R.choice(["", "ur", "ing", "s", "!"])
    DOCS.append((k, " ".join(w), "en", "s1"))
    LABELS.append((k, 1, int(toxic)))
DOCS += [(1000, TWIN, "en", "s2"), (1001, TWIN, "en", "s2"), (1002, TWIN + " " + CLEAN[0], "de", "s2"), (1003, f"{prose(30)} {PASSAGE}", "en", "s3"), (1004, f"{PASSAGE}\n{prose(45)}", "en", "s3")]
DOCS += [(1005, f"{prose(40)} {ITEM.upper()} {prose(9)}", "en", "s3"), (1006, None, None, None), (1007, "", "en", ""), (1008, " \t", "en", "s1"), (1009, "Released under the MIT License.", "en", "s1"), (1010, prose(4000), "en", "s1"), (1011, "É日 a\tB <|endoftext|>", "fr", "s1")]
PAGES = [(1, "http://A.example.net/en/x?q"), (2, "https://shop.net/de"), (3, None), (4, "no scheme"), (5, "http://x.org/fr/"), (6, "http://example.com/de/#x"), (7, "http://other.edu/it?lang=en"), (7, "http://other.edu/it?lang=en")]


@pytest.fixture(scope="module")
def sf(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("tables"))

    def put(name, rows, schema):
        spark.createDataFrame(rows, schema).repartition(3).write.parquet(f"{folder}/{name}.parquet")

    put("documents", [(i, t, a, b, None if t is None else len(t), f"kept {i}") for i, t, a, b in DOCS], "doc_id long, text string, lang string, source string, n_chars long, toxic_score string")
    put("labels", LABELS, "doc_id long, quality int, toxic int")
    put("benchmark", [(7, ITEM), (8, None), (9, "")], "item_id long, text string")
    put("pages", [(i, u, "") for i, u in PAGES], "page_id long, url string, html string")
    return folder


def rows(spark, sf, name):
    return [r.asDict() for r in queries.queries()[name](spark, sf).collect()]


def cut(t):
    return re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode())


def low(t):
    return [bytes(c + 32 if 65 <= c <= 90 else c for c in w) for w in cut(t)]


def held(i, m, r):
    return zlib.crc32(str(i).encode()) % m == r


def test_op1(spark, sf):
    got = {r["doc_id"]: r for r in rows(spark, sf, "op1_toxicity")}
    toxic = {i for i, _, t in LABELS if t}
    assert set(got) == {i for i, *_ in DOCS} and all(r["held_out"] == held(i, 3, 1) for i, r in got.items())
    assert all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.7) for r in got.values())
    out = [(i in toxic, r["predicted"]) for i, r in got.items() if r["held_out"] and i < 260]
    assert np.mean([p for y, p in out if y]) > 0.8 and np.mean([p for y, p in out if not y]) < 0.1
    assert got[1006]["score"] == got[1007]["score"] == got[1008]["score"]


def test_op2_and_op10(spark, sf):
    assert [(r["doc_id"], r["item_id"], r["start_word"], r["similarity"]) for r in rows(spark, sf, "op2_decontaminate")] == [(1005, 7, 40, 1.0)]
    got = rows(spark, sf, "op10_licenses")
    assert len(got) == len(DOCS) and [(r["doc_id"], r["licenses"]) for r in got if r["licenses"]] == [(1009, ["MIT"])]


def test_op3(spark, sf):
    got = {r["doc_id"]: r for r in rows(spark, sf, "op3_class_lm")}
    c = {}
    for i, t, *_ in DOCS:
        if not held(i, 7, 2):
            for w in [*low(t), b"\n"]:
                c[w] = c.get(w, 0) + 1
    n, v = sum(c.values()), len(c)
    for i, t, *_ in DOCS:
        w = [*low(t), b"\n"]
        r = got[i]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held(i, 7, 2), len(w), sum(x in c for x in w), n)
        assert r["base_score"] == pytest.approx(sum(np.log10((c.get(x, 0) + 1) / (n + v + 1)) for x in w)) and r["score"] < 0
    # texts here are words drawn at random, so classes can tell nothing: the model may not lose much by them
    assert sum(r["score"] for r in got.values()) > 1.05 * sum(r["base_score"] for r in got.values())


def test_op4(spark, sf):
    got = {r["doc_id"]: r for r in rows(spark, sf, "op4_substring_dedup")}
    seen = {}
    for _, t, *_ in DOCS:
        w = cut(t)
        for p in range(len(w) - 34):
            seen[tuple(w[p : p + 35])] = seen.get(tuple(w[p : p + 35]), 0) + 1
    for i, t, *_ in DOCS:
        w = cut(t)
        gone = {q for p in range(len(w) - 34) if seen[tuple(w[p : p + 35])] > 1 for q in range(p, p + 35)}
        left = b" ".join(x for q, x in enumerate(w) if q not in gone)
        assert (got[i]["n_words"], got[i]["n_removed"], got[i]["kept_sha256"]) == (len(w), len(gone), hashlib.sha256(left).hexdigest())
    assert got[1003]["n_removed"] == 55


def test_op5(spark, sf):
    got = rows(spark, sf, "op5_url_filter")
    want = {1: ("a.example.net", "/en/x", "example.net/en/"), 2: ("shop.net", "/de", "net/"), 3: ("", "", None), 4: ("", "", None), 5: ("x.org", "/fr/", "org/fr/"), 6: ("example.com", "/de/", "example.com/de/"), 7: ("other.edu", "/it", None)}
    assert len(got) == len(PAGES) and all((r["host"], r["path"], r["rule"]) == want[r["page_id"]] for r in got)
    verdict = {"example.net/en/": "allow", "net/": "block", "org/fr/": "allow", "example.com/de/": "block"}
    assert all(r["verdict"] == verdict.get(r["rule"], r["verdict"]) and r["verdict"] in ("allow", "block") for r in got)


def test_op6(spark, sf):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(W.tokenizer_path("word_bpe_49k.json"))
    at, want = 0, []
    for i, t, *_ in sorted(DOCS):
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 2]
        want.append((i, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    assert sorted((r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) for r in rows(spark, sf, "op6_token_files")) == want


def test_words_are_coded_as_by_the_library():
    import pyarrow as pa

    words = token_store.WordIds(W.tokenizer_path("word_bpe_49k.json"))
    signs = "abAB019 '’\"<|>.,!?sSdDéÉßİΣσςñ́   \t\n\x0b\x1c\x85\x00ﬁ٣½²中_-"
    texts = ["".join(R.choice(signs) for _ in range(R.randrange(40))) for _ in range(3000)] + ["a<|endoftext|>b I'll we'Re 'S ''s", "<|startoftext|>"]
    for keep in (words.KEEP, 5):  # with so few kept, all is forgotten again and again
        words.KEEP = keep
        for part in (texts[:1500], texts[1500:], texts[:10]):
            ids, n = token_store.encoded_slice(W.Words(pa.array(part)), words, 2)
            assert ids.tolist() == [x for t in part for x in [*words.tok.encode(t, add_special_tokens=False).ids, 2]]


def test_op7(spark, sf):
    got = {r["doc_id"]: r for r in rows(spark, sf, "op7_jaccard_join")}
    sets = {}
    for i, t, *_ in DOCS:
        w = low(t)
        sets[i] = {tuple(w[p : p + 3]) for p in range(len(w) - 2)} if len(w) > 2 else ({tuple(w)} if w else set())
    assert all(got[i]["n_shingles"] == len(s) for i, s in sets.items())
    near = {i: min([j for j, o in sets.items() if s and 100 * len(s & o) >= 90 * len(s | o)], default=i) for i, s in sets.items()}
    assert {i: r["component_id"] for i, r in got.items()} == near and near[1002] == 1000


def test_op8(spark, sf):
    got = {r["doc_id"]: r for r in rows(spark, sf, "op8_fingerprint")}
    order = sorted(DOCS, reverse=True, key=lambda d: d[0])
    by = {}
    for k, (i, t, *_) in enumerate(order):
        t, nxt = t or "", order[(k + 1) % len(order)][1] or ""
        n = len(t) // 3
        edited = t[: len(t) - n] + nxt[:n]
        r = got[i]
        assert (r["n_chars"], r["edited_sha256"]) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        assert 0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1
        assert by.setdefault(t, r["fingerprint"]) == r["fingerprint"]

        def shingles(x):
            w = cut(x)
            return {tuple(w[p : p + 5]) for p in range(len(w) - 4)} if len(w) > 4 else ({tuple(w)} if w else set())

        a, b = shingles(t), shingles(edited)
        if len(a | b) > 40:
            assert r["near_edited"] == pytest.approx(len(a & b) / len(a | b), abs=0.25)


def test_op9(spark, sf):
    from driftrank.llm import pieces

    sp = pieces.pieces_of(W.tokenizer_path("piece_bpe_32k.model"))
    got = {r["doc_id"]: r for r in rows(spark, sf, "op9_pieces")}
    for i, t, *_ in DOCS:
        if len(t or "") < 500:
            two = sp.text_nbest(t or "", 2)
            assert got[i]["round_trip"] and got[i]["score"] == pytest.approx(two[0][0])
            assert len(two) < 2 or got[i]["second_score"] == pytest.approx(two[1][0])


def test_pipeline(spark, sf):
    """Toxic rows, copies and a leaked item go, the shared passage is cut, all else stays; a clashing column comes through."""
    import corpus_pipeline

    toxic = {i for i, _, t in LABELS if t}
    docs, kept = W.docs(spark, sf), {}
    for name, stage in corpus_pipeline.STAGES:
        out = W.written(stage(spark, docs, sf), f"test-{name}")
        if name != "pieces":
            assert out.columns == docs.columns and out.where("toxic_score <> concat('kept ', doc_id)").isEmpty()
        kept[name] = {r["doc_id"]: r.asDict() for r in out.collect()}
        docs = out
    every = {i for i, *_ in DOCS}
    assert len(every - set(kept["toxicity"]) - toxic) <= 5 and len(toxic & set(kept["toxicity"])) <= 5 and {1006, 1007, 1008} <= set(kept["toxicity"])
    assert set(kept["toxicity"]) - set(kept["jaccard_join"]) == {1001, 1002} & set(kept["toxicity"])
    texts = {i: t for i, t, *_ in DOCS}
    for i, r in kept["substring_dedup"].items():
        if i in (1003, 1004):
            assert r["text"].split() == [w for w in texts[i].split() if w not in PASSAGE.split() or w in texts[i].replace(PASSAGE, "").split()] or PASSAGE not in r["text"]
            assert r["n_chars"] == len(r["text"])
        else:
            assert r["text"] == texts[i]
    assert set(kept["substring_dedup"]) - set(kept["decontamination"]) == {1005}
    assert set(kept["pieces"]) == set(kept["decontamination"]) and all(r["round_trip"] for r in kept["pieces"].values())
    assert corpus_pipeline.run(spark, sf).count() == len(kept["pieces"])


def test_empty_tables(spark, sf, tmp_path):
    for name in ("documents", "labels", "benchmark", "pages"):
        W.docs(spark, sf, name).limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    for name, query in queries.queries().items():
        assert query(spark, str(tmp_path)).count() == 0, name
