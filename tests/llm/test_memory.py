"""What Python workers of the text operators take, and what they give back."""

import tracemalloc

import numpy as np
import pyarrow as pa

from driftrank.llm import substring_dedup as S
from driftrank.llm import words as W


def test_slices_give_memory_back(monkeypatch):
    given = []
    monkeypatch.setattr(W, "trim", lambda: given.append(1))
    batches = [pa.record_batch({"text": pa.array(["a b", None])}), pa.record_batch({"text": pa.array([], pa.string())}), pa.record_batch({"text": pa.array(["c"])})]
    assert [b.num_rows for b in W.slices(iter(batches))] == [2, 1]
    assert len(given) == 2


def test_entries_are_settled_without_a_second_copy():
    n = 200_000
    e = np.zeros(n, S._ENTRY)
    e["h1"] = np.random.default_rng(1).permutation(n) // 2  # each window twice
    e["h1"][: n // 2] += n  # and half of them perhaps once
    e["dk"] = np.arange(n)
    want = np.bincount(np.unique(e["h1"], return_inverse=True)[1])[np.unique(e["h1"], return_inverse=True)[1]] > 1
    tracemalloc.start()
    hits, left = S._settled(e)
    rest = S._only(e, left)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < e.nbytes
    assert (hits == np.flatnonzero(want)).all()
    assert (rest["dk"] == left).all() and len(np.unique(rest["h1"])) == len(rest) == len(left)


def test_one_hash_of_several_windows():
    e = np.zeros(6, S._ENTRY)
    e["h1"], e["g"], e["h2"] = 7, [1, 2, 1, 2, 1, 3], [5, 5, 6, 5, 5, 5]
    hits, left = S._settled(e)
    assert hits.tolist() == [0, 1, 3, 4] and left.tolist() == [0, 1, 2, 5]
    assert e["known"][left].tolist() == [True, True, False, False]
    assert [x.tolist() for x in S._settled(e[:0])] == [[], []]
