"""The index of a benchmark: its size, long items, and windows that repeat."""

import pickle
import random

import numpy as np
import pytest

from ldpspark.llm import decontaminate as D


def brute(items, text, n=13):
    words = lambda t: [w.decode() for w in D.C.ascii_words((t or "").encode())]
    w, hit, found = words(text), set(), set()
    for k, t in items:
        v = words(t)
        size = min(n, len(v))
        grams = {tuple(v[i : i + size]) for i in range(len(v) - size + 1)} if v else set()
        for i in range(len(w) - size + 1 if size else 0):
            if tuple(w[i : i + size]) in grams:
                hit |= set(range(i, i + size))
                found.add(k)
    return [i in hit for i in range(len(w))], found


def test_index_size_is_bounded():
    rng = random.Random(1)
    items = [(k, " ".join(f"w{rng.randrange(50_000)}" for _ in range(200))) for k in range(2000)]
    index, size = D.Index(items), sum(len(t) for _, t in items)
    assert index.nbytes() <= D.INDEX_BYTES * size and len(pickle.dumps(index)) <= D.INDEX_BYTES * size
    letters = [(k, " ".join(rng.choice("abcdefgh") for _ in range(5000))) for k in range(20)]
    assert D.Index(letters).nbytes() <= D.INDEX_BYTES * sum(len(t) for _, t in letters)


@pytest.mark.parametrize("chunk", [D.CHUNK, 50])
def test_scan_against_brute_force(monkeypatch, chunk):
    monkeypatch.setattr(D, "CHUNK", chunk)
    D._powers.cache_clear()
    rng = random.Random(2)
    words = ["alpha", "beta", "\u00e9t\u00e9", "x1"]
    items = [(k, " ".join(rng.choice(words) for _ in range(rng.choice([1, 2, 5, 12, 13, 14, 40])))) for k in range(15)] + [(15, "omega " * 30), (16, "Omega, omega")]
    texts = [" ".join(rng.choice([*words, "omega", "ZZ"]) for _ in range(rng.choice([0, 1, 12, 13, 300]))) for _ in range(40)] + [items[6][1].upper() + "!", "omega\n" * 14]
    got = D.scan_texts(D.Index(items), [t.encode() for t in texts])
    assert [(m.tolist(), {int(k) for k in x}) for m, x in got] == [brute(items, t) for t in texts]
    D._powers.cache_clear()


def test_equal_hashes_are_verified(monkeypatch):
    monkeypatch.setattr(D, "window_hashes", lambda words, size: np.full(max(0, len(words) - size + 1), 7, np.uint64))
    items = [(0, " ".join(f"a{i}" for i in range(13))), (1, " ".join(f"b{i}" for i in range(14)))]
    texts = [items[0][1] + " c", "d " * 20, items[1][1]]
    got = D.scan_texts(D.Index(items), [t.encode() for t in texts])
    assert [(m.tolist(), x) for m, x in got] == [brute(items, t) for t in texts]


def test_long_items_are_cut_into_parts_that_lose_no_window(spark):
    rng = random.Random(4)
    long = " ".join(f"w{rng.randrange(40)}" for _ in range(400))
    bench = spark.createDataFrame([(1, long), (2, "short one"), (3, None)], "item_id long, text string")
    words = long.split()
    df = spark.createDataFrame([(i, "x " + " ".join(words[i * 7 : i * 7 + 13 + i % 3]) + " y") for i in range(50)] + [(99, "a short one")], "doc_id long, text string")
    whole, parts = ({r["doc_id"]: (r["n_hit"], r["items"]) for r in D.contamination(df, bench, slice_bytes=b).collect()} for b in (D.SLICE_BYTES, 600))
    assert whole == parts and all(n >= 13 for k, (n, _) in whole.items() if k < 50) and whole[99] == (2, ["2"])
    for own, size in D._parts(long, 600, 13):
        assert size == len(own) + 1 and len(own) <= 600
