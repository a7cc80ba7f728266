"""The whole toxicity query against a plain fit and scan, and stems that end between letters."""

import math
import zlib
from collections import Counter

import numpy as np
import pytest

from ldpspark.llm import common as C
from ldpspark.llm import toxicity as T


def best_segments(values, lo=0):
    """Maximal segments by definition: the best one, then the same to its left and right."""
    if not len(values) or values.max() <= 1e-12:
        return []
    total = np.concatenate(([0.0], np.cumsum(values)))
    low = np.minimum.accumulate(total)
    end = int((total - low).argmax())
    start = int(total[: end + 1].argmin())
    return [*best_segments(values[:start], lo), total[end] - total[start], *best_segments(values[end:], lo + end)]


def test_query_against_brute_force(spark):
    sf = "/root/testdata/sf0.01"
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect() if r["toxic"] is not None}
    held = {i: zlib.crc32(str(i).encode()) % 5 == 0 for i in texts}
    train = sorted({(texts[i], y) for i, y in labels.items() if not held[i]})
    count = {y: Counter(f for t, x in train if x == y for f in T.features(t)) for y in (0, 1)}
    total = {y: sum(count[y].values()) for y in (0, 1)}
    words = {y: sum(n for f, n in count[y].items() if not f.endswith(b"*")) for y in (0, 1)}
    score, share, prior = {}, {}, 0.2 * sum(total.values())
    for f in count[0].keys() | count[1].keys():
        t, o = count[1][f], count[0][f]
        a = 0.2 * (t + o)
        odds = math.log((t + a) / (total[1] + prior - t - a)) - math.log((o + a) / (total[0] + prior - o - a))
        z = odds / math.sqrt(1 / (t + a) + 1 / (o + a))
        if abs(z) > 2:
            score[f] = odds * (1 - 4 / z**2)
            if not f.endswith(b"*"):
                share[f] = (o + a) / (words[0] + 0.2 * (words[0] + words[1]))

    def segments(text):
        w = C.ascii_words(text)
        own = [score.get(x, next((score[k] for n in (6, 5, 4) if (k := T.stem(x, n)) in score), 0.0)) - 0.3 for x in w]
        return len(w), best_segments(np.array(own))

    mean = lambda x: sum(p * math.exp(x * (score[f] - 0.3)) for f, p in share.items()) + (1 - sum(share.values())) * math.exp(-0.3 * x)
    lam, step = 1e-3, 1e-3
    while mean(lam) < 1:
        lam *= 2
    lo, hi = lam / 2, lam
    for _ in range(60):
        lo, hi = ((lo + hi) / 2, hi) if mean((lo + hi) / 2) < 1 else (lo, (lo + hi) / 2)
    maxima = [lam2 - math.log(n) for lam2, n in ((hi * max(s, default=0.0), n) for n, s in (segments(t) for t, y in train if y == 0)) if n]
    k = math.exp(min(sum(maxima) / len(maxima) - np.euler_gamma, 0))
    excess = {}
    for i, t in texts.items():
        n, found = segments(t)
        excess[i] = sum(max(0.0, hi * s - math.log(max(k * n, 1.0))) for s in found)
    by_text = {t: excess[i] for i, t in texts.items()}
    a, b = T.logistic(np.array([by_text[t] for t, _ in train]), np.array([float(y) for _, y in train]))
    drawn, known = Counter(y for _, y in train), Counter(y for i, y in labels.items() if not held[i])
    a -= math.log((drawn[1] / known[1]) / (drawn[0] / known[0]))
    got = {r["doc_id"]: r for r in T.op5_toxicity(spark, sf).collect()}
    assert set(got) == set(texts) and step
    for i in texts:
        want = 1 / (1 + math.exp(-(a + b * excess[i])))
        assert got[i]["score"] == pytest.approx(want, abs=1e-4) and got[i]["held_out"] == held[i]


def test_stems_end_between_letters():
    word = "\u00e9t\u00e9s\u4e2d\u6587x".encode()
    found = [T.stem(word, n) for n in T.STEMS]
    assert all(s[:-1].decode() and word.startswith(s[:-1]) for s in found) and T.stem("abcdé".encode(), 5) is None and T.stem(b"abcd", 4) is None
    assert T.stem(b"abcde", 4) == b"abcd*"
