"""Cases that a shorter job would miss."""

import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from driftrank.llm import decontaminate, licenses, pieces, toxicity, url_filter
from driftrank.llm import words as W

R = random.Random(11)


def text(n):
    return " ".join(f"v{R.randrange(5000)}" for _ in range(n))


def test_leaks_equal_brute_force_with_texts_shorter_than_the_item(spark):
    items = {1: text(54), 2: text(12), 3: text(7), 4: text(3)}
    rows = []
    for item in items.values():
        w = item.split()
        for n in range(1, len(w) + 1):
            rows += [" ".join(w[:n]), " ".join(w[len(w) - n :])]
        rows += [f"{text(9)} {item} {text(9)}", f"{text(4)} {' '.join(w[1:])}"]
    frame = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string").repartition(3)
    got = {(r["doc_id"], r["item_id"]): r["similarity"] for r in decontaminate.find_leaks(frame, spark.createDataFrame(list(items.items()), "item_id long, text string")).collect()}

    def bag(w, k):
        out = {}
        for i in range(len(w) - k + 1):
            out[tuple(w[i : i + k])] = out.get(tuple(w[i : i + k]), 0) + 1
        return out

    want = {}
    for d, t in enumerate(rows):
        for i, item in items.items():
            w, v = t.split(), item.split()
            k = min(5, len(v))
            b, best = bag(v, k), 0.0
            for at in range(max(1, len(w) - len(v) + 1)):
                a = bag(w[at : at + len(v)], k)
                low = sum(min(n, b.get(g, 0)) for g, n in a.items())
                best = max(best, low / max(1, sum(a.values()) + sum(b.values()) - low))
            if best >= 0.8:
                want[d, i] = best
    assert got == want
    cut = rows.index(" ".join(items[1].split()[:46]))
    assert got[cut, 1] == 42 / 50


def test_both_paths_equal_the_search_over_the_whole_text(spark):
    sp = pieces.pieces_of(W.tokenizer_path("piece_bpe_32k.model"))
    words = sorted({R.choice(["un", "re", "in", "the", "an"]) + "".join(R.choice("aeinorst") for _ in range(R.randint(2, 9))) for _ in range(200)})
    rows = words + [f"of {w}  and" for w in words] + ["   ", "a    b ", "  two", "x" * 300, " " * 100, "æ日本 ☃", ""]
    got = pieces.encode_documents(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")).collect()
    assert len(got) == len(rows)
    for r in got:
        assert r["second_crc32"] is None or r["second_crc32"] != r["ids_crc32"]
        two, own = sp.text_nbest(rows[r["doc_id"]], 2), np.frombuffer(r["ids"], sp.width).tolist()
        assert r["score"] == pytest.approx(two[0][0]) and (len(two) < 2 or r["second_score"] == pytest.approx(two[1][0]))
        if len(two) > 1 and two[0][0] - two[1][0] > 1e-9:
            assert own == two[0][1] and r["round_trip"] and r["n_pieces"] == len(own)
        if len(two) > 1 and two[0][0] - two[1][0] > 1e-9 and (len(three := sp.text_nbest(rows[r["doc_id"]], 3)) < 3 or three[1][0] - three[2][0] > 1e-9):
            assert r["second_crc32"] == zlib.crc32(np.array(two[1][1], "<u4").tobytes())


def test_ordinary_words_are_cut_as_by_the_library():
    import sentencepiece

    path = W.tokenizer_path("piece_bpe_32k.model")
    lib, sp = sentencepiece.SentencePieceProcessor(model_file=path), pieces.pieces_of(path)
    for w in ("Hello there world", "the people  of the country", "information about government companies"):
        ids = sp.text_nbest(w, 1)[0][1]
        assert ids == lib.encode(w) and sp.decode(np.array(ids)) == lib.decode(ids) == w


def test_every_known_sentence_and_rule_on_one_line_and_wrapped(spark):
    rows, want = [], []
    for k, v in licenses.SENTENCES.items():
        for s in v:
            w = s.split()
            rows += [s, f"Intro. {s}\nMore", " * " + "\n * ".join(" ".join(w[i : i + 4]) for i in range(0, len(w), 4)) + "\r\n * more", "# " + "\r\n# ".join(w), f"x {s}", s.rstrip(".:;") + " not"]
            want += [k, k, k, k, "", ""]
    got = {r["doc_id"]: r["sentence_ids"].strip() for r in licenses.scan(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")).collect()}
    assert [got[i] for i in range(len(rows))] == want
    texts = ["\n".join(licenses.SENTENCES[k][0] for k in rule.split()) for _, rule in licenses.RULES]
    got = {r["doc_id"]: r for r in licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    for i, (name, rule) in enumerate(licenses.RULES):
        assert got[i]["licenses"] == [name] and got[i]["sentence_ids"].split() == rule.split() and got[i]["permissive"] == (name in licenses.PERMISSIVE)


def test_licence_tables_are_parameters_and_odd_rows(spark):
    own = {"a": ["Use it as you like"], "b": ["Keep this line."]}
    rows = [(1, "Use it as you like\nand\nKeep this line.", "x"), (2, "Keep this line.", None), (3, None, "y"), (3, None, "y"), (4, "use it. as you LIKE!", "z")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, licenses string")
    out = licenses.scan(frame, own, [("Own", "a b"), ("Part", "a")], {"Own"})
    got = sorted((r["doc_id"], r["licenses"], r["permissive"]) for r in out.collect())
    assert got == [(1, ["Own"], True), (2, [], None), (3, [], None), (3, [], None), (4, ["Part"], False)]
    assert licenses.scan(frame.limit(0)).count() == 0
    plan = licenses.scan(frame)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan
    with pytest.raises(ValueError):
        licenses.scan(frame, own, [("Own", "a c")])


def test_toxicity_learns_from_whole_texts(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "SAMPLE_WORDS", 3000, raising=False)  # was the words of all rows together
    clean = ["".join(R.choice("abcdeghik") for _ in range(R.randint(2, 7))) for _ in range(300)]
    rows, tags = [], []
    for k in range(600):
        w = [R.choice(clean) for _ in range(R.randint(20, 50))]
        if k % 3 == 0:
            w[-R.randint(1, 5)] = "vloot" + R.choice(["", "ur", "ing", "s"])
        rows.append((k, " ".join(w)))
        tags.append((k, int(k % 3 == 0)))
    m = toxicity.train(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(tags, "doc_id long, toxic int"), F.col("doc_id") < 480)
    s, y = m.scores(pa.array([t for _, t in rows[480:]])), np.array([t for _, t in tags[480:]])
    assert np.median(s[y == 1]) > np.quantile(s[y == 0], 0.9)


def test_urls_are_scored_whole(spark):
    rows = [(k, f"http://s{k}.example.net/en/{k}?lang=de") for k in range(30)] + [(100 + k, f"http://s{k}.net/{k}?lang=fr") for k in range(30)]
    rows += [(200, "http://x.edu/a?lang=de"), (201, "http://x.edu/a?lang=fr"), (202, "no scheme ?lang=de"), (203, "no scheme ?lang=fr"), (204, None), (205, "")]
    got = {r["page_id"]: r for r in url_filter.filter_urls(spark.createDataFrame(rows, "page_id long, url string")).collect()}
    assert got[200]["ratio"] > got[201]["ratio"] and got[202]["ratio"] > got[203]["ratio"]
    assert got[204]["ratio"] == got[205]["ratio"] and got[204]["rule"] is None and (got[202]["host"], got[202]["path"]) == ("", "")
