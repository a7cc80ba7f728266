"""The whole language query against hyperdimensional vectors put together one by one."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from ldpspark.llm import common as C
from ldpspark.llm import language_id as L


def vector(text, symbol, first, second, third):
    """Sum over the trigrams of a text, each the product of its letters' rotated vectors; borders around words are a letter."""
    s, kept = [0, *(symbol.get(c, 1 if c.isalpha() else 0) for c in text.lower()), 0], []
    for x in s:
        if x or not kept or kept[-1]:
            kept.append(x)
    out = np.zeros(first.shape[1])
    for a, b, c in zip(kept, kept[1:], kept[2:], strict=False):
        if b:
            out += first[a] * second[b] * third[c]
    return out


def test_query_against_brute_force(spark):
    sf = "/root/testdata/sf0.001"
    rows = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", C.held_out(F.col("doc_id")).alias("h")).collect()
    train = [r for r in rows if not r["h"] and r["lang"] is not None]
    letters = Counter(c for r in train for c in (r["text"] or "").lower() if c.isalpha())
    common = sorted(ord(c) for c, _ in sorted(letters.items(), key=lambda x: (-x[1], ord(x[0])))[: L.ALPHABET - 2])
    symbol, third = {chr(c): k for k, c in enumerate(common, 2)}, L.bind(L.ALPHABET, L.DIMENSIONS, L.SEED).astype(float)
    turned = (np.roll(third, 2, axis=1), np.roll(third, 1, axis=1), third)
    own = {r["doc_id"]: vector(r["text"] or "", symbol, *turned) for r in rows}
    prototype = {x: sum(own[r["doc_id"]] for r in train if r["lang"] == x) for x in sorted({r["lang"] for r in train})}
    got = {r["doc_id"]: r for r in L.op6_language_id(spark, sf).collect()}
    assert len(got) == len(rows)
    for r in rows:
        v, g = own[r["doc_id"]], got[r["doc_id"]]
        if not any(c.isalpha() for c in r["text"] or ""):
            assert (g["lang_pred"], g["score"]) == ("und", 0)
            continue
        cosine = {x: v @ p / np.linalg.norm(v) / np.linalg.norm(p) for x, p in prototype.items()}
        best = max(cosine, key=cosine.get)
        assert g["held_out"] == r["h"] and g["lang_pred"] == best and g["score"] == pytest.approx(max(0, cosine[best]), abs=1e-5)


def test_lengths_in_groups(monkeypatch):
    rng = np.random.default_rng(6)
    vectors, sizes = L.bind(5, 300, 1), [3, 1, 700, 0, 40, 2]
    codes = rng.integers(0, 125, sum(sizes))
    bounds = np.cumsum([0, *sizes])
    first, second = np.roll(vectors, 2, axis=1), np.roll(vectors, 1, axis=1)
    want = [np.linalg.norm((first[c // 25] * second[c // 5 % 5] * vectors[c % 5]).sum(axis=0)) for c in (codes[a:b] for a, b in zip(bounds, bounds[1:], strict=False))]
    for group, most, rows, part in ((64, 60_000, 4096, 512), (2, 5, 7, 64), (1, 1, 1, 1)):
        for name, value in (("GROUP", group), ("GROUP_CODES", most), ("ROWS", rows), ("PART", part)):
            monkeypatch.setattr(L, name, value)
        assert L.lengths(codes, bounds, vectors) == pytest.approx(want)
