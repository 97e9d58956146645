"""Words that several slices hold travel once; answers go back in pieces."""

import numpy as np
import pyarrow as pa

from driftrank.llm import class_lm
from driftrank.llm import words as W


def test_neighbours_of_a_word_come_in_one_row_for_all_slices():
    a = np.array([7, -3]), np.array([1, 2]), np.array([[1, 2], [3, 4], [5, 6]], np.uint8)
    b = np.array([-3, 9]), np.array([1, 1]), np.array([[7, 8], [9, 10]], np.uint8)
    h, cut, near = class_lm.merged([a, b])
    flat = near.reshape(-1)
    assert {int(w): flat[lo:hi].tolist() for w, lo, hi in zip(h, cut, cut[1:])} == {-3: [3, 4, 5, 6, 7, 8], 7: [1, 2], 9: [9, 10]}
    h, cut, near = class_lm.merged([(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, 2), np.uint8))])
    assert len(h) == 0 and cut.tolist() == [0]


def test_answers_travel_as_one_row_a_slice_and_task():
    rng = np.random.default_rng(3)
    want = {at: (rng.integers(0, 1 << 33 if at == 7 else 1 << 20, n), rng.integers(0, class_lm.KINDS, n)) for at, n in ((1, 300), (7, 70_000), (1 << 33, 1))}
    rows = [(at, k, int(c[k]), int(cls[k])) for at, (c, cls) in want.items() for k in range(len(c))]
    kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int32()]
    sent = []
    for task in range(3):
        own = [r for r in rows if r[1] % 3 == task]  # sorted by slice and place
        batches = [pa.record_batch([pa.array(x, t) for x, t in zip(zip(*own[lo : lo + 5000]), kinds)], ["slice", "k", "c", "cls"]) for lo in range(0, len(own), 5000)]
        sent += class_lm.pieces(batches)
    assert len(sent) == 3 + 2 + 2 and all(b.num_rows == 1 for b in sent)
    got = {}
    for b in class_lm.assembled(sorted(sent, key=lambda b: b.column(0)[0].as_py())):
        cls = np.frombuffer(b.column(2)[0].as_py(), "u1")
        raw = np.frombuffer(b.column(1)[0].as_py(), "u1")
        got[b.column(0)[0].as_py()] = raw.view("<u4" if len(raw) == 4 * len(cls) else "<i8").tolist(), cls.tolist()
    assert got == {at: (c.tolist(), cls.tolist()) for at, (c, cls) in want.items()}


def test_shuffles_of_the_lookup_are_freed(spark):
    import time

    held = lambda: spark.sparkContext._jsc.sc().env().mapOutputTracker().shuffleStatuses().size()
    docs = spark.createDataFrame([(i, f"a b c{i} d{i % 7}") for i in range(200)], "doc_id long, text string")
    W.freed(spark)
    time.sleep(1)
    before = held()
    slices = W.written(class_lm.coded(docs, class_lm.F.lit(True)), "coded")
    words = W.written(class_lm.word_counts(slices).withColumn("cls", class_lm.F.lit(2)), "words")
    replies = class_lm.answers(slices, words)
    assert class_lm.learnt_rows(slices) == 200
    until = time.time() + 10
    while held() > before + 1 and time.time() < until:  # one of the sum of learnt rows may be left
        W.freed(spark)
        time.sleep(0.2)
    assert held() <= before + 1
    ready = class_lm.answered(slices, replies)
    assert ready.columns == ["slice", "ids", "learn", "starts", "low", "high", "c", "cls"]
