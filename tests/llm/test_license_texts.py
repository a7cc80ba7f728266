"""Signatures on the words of well-known licenses, letters beyond ASCII, and texts with very many detections."""

import time

import pytest

from ldpspark.llm import license_scan as L

TEXTS = [
    ("mit", "The above copyright notice and this permission notice shall be included in all copies or substantial portions"), ("bsd", "Redistributions in binary form must reproduce the above copyright notice, this list"),
    ("bsd-3-clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products"), ("bsd-4-clause", "All advertising materials mentioning features or use of this software must display the following acknowledgement:"),
    ("apache-2.0", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS"), ("gpl-2.0-or-later", "GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("zlib", "The origin of this software must not be misrepresented"), ("unlicense", "This is free and unencumbered software released into the public domain."), ("json", "The Software shall be used for Good, not Evil."), ("gpl-with-classpath-exception", "with Classpath Exception"),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"), ("epl-2.0", "which is available at https://www.eclipse.org/legal/epl-2.0/"), ("proprietary", "PROPRIETARY AND CONFIDENTIAL"), ("ofl-1.1", "with Reserved Font Name Foo"),
    ("cc0-1.0", "To the extent possible under law, Jane Doe has waived all copyright and related or neighboring rights to Work"), ("wtfpl", "0. You just DO WHAT THE F you want to."), ("cc", "Some rights reserved"), ("hpnd", "PERMISSION TO USE, COPY, MODIFY, AND DISTRIBUTE THIS SOFTWARE AND ITS DOCUMENTATION for any purpose"),
]


def test_signatures_of_license_texts(spark):
    df = spark.createDataFrame([(k, t) for k, (_, t) in enumerate(TEXTS)], "doc_id long, text string")
    got = {r["doc_id"]: r["labels"] for r in L.scan(df).collect()}
    assert [(x, got[k]) for k, (x, _) in enumerate(TEXTS) if x not in got[k]] == []
    assert len(L.SIGNATURES) >= 90


def test_only_ascii_letters_are_lowered(spark, duck):
    texts = ["ALL RIGHTS RESERVED", "all r\u0130ghts reserved", "all rights reserved\u00c9", "LIC\u212aENSE cc by", "CC BY \u00c9 Cc bY"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = [(r["n_base"], r["n_words"]) for r in L.scan(df).orderBy("doc_id").collect()]
    assert got == [(1, 3), (0, 3), (0, 3), (1, 3), (2, 5)]


@pytest.mark.parametrize("n", [127, 128, 129, 300])
def test_runs_of_the_sweep(spark, n):
    """A long detection around short ones, and as many as cross the border of a run."""
    text = "x " + "cc by 4.0 y " * n + "gnu lesser general public license version 2.1 z " + "gpl w " * n
    r = L.scan(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()
    words = text.replace(".", " ").split()
    want = [(i, i + 3, "cc-by-4.0") for i in range(len(words)) if words[i : i + 2] == ["cc", "by"]]
    assert [(d["first"], d["last"], d["label"]) for d in r["detections"] if d["label"] == "cc-by-4.0"] == want
    assert not any(d["label"] == "gpl" and words[d["first"]] == "gnu" for d in r["detections"])
    assert sum(d["label"] == "gpl" for d in r["detections"]) == n


def test_many_detections_take_linear_time(spark):
    took = []
    for n in (10_000, 40_000):
        df = spark.createDataFrame([(1, "cc by 4.0 some text " * n)], "doc_id long, text string")
        start = time.time()
        assert L.scan(df).first()["n_base"] == n
        took.append(time.time() - start)
    assert took[1] < 8 * took[0] + 2 and took[1] < 30


def test_keys_hold_for_all_other_gates():
    assert all(any(f" {k} " in f" {x.strip()} " for k in L.KEYS) for x in L.ANY if x not in L.GATES)
    assert all(x in L.ANY or any(y in x for y in L.ANY) for x in L.GATES)
