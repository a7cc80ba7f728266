"""Gates must not hide what rules find."""

import re

from ldpspark.llm import common as C
from ldpspark.llm import license_scan as L

TEXTS = [
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("gpl-3.0", "It is released under the GNU GPL v3 and nothing else."), ("mpl-2.0", "See https://mozilla.org/MPL/2.0/ for terms"), ("epl-1.0", "http://www.eclipse.org/legal/epl-v10.html"),
    ("ofl-1.1", "Fonts: http://scripts.sil.org/OFL"), ("proprietary", "This software is proprietary."), ("proprietary", "this software is confidential"), ("unknown", "Distributed under the terms below"),
    ("non-commercial", "for non-commercial use"), ("non-commercial", "for noncommercial purposes"), ("unlicense", "unlicense.org"), ("cc-by-sa", "https://creativecommons.org/licenses/by-sa/"),
]


def test_texts_without_the_keyword(spark):
    df = spark.createDataFrame([(k, t) for k, (_, t) in enumerate(TEXTS)], "doc_id long, text string")
    got = {r["doc_id"]: r["labels"] for r in L.scan(df).collect()}
    assert [x for k, (x, _) in enumerate(TEXTS) if x not in got[k]] == []


def test_gated_and_ungated_rules_agree(spark, sf):
    texts = [t for _, t in TEXTS] + [r["text"] or "" for r in spark.read.parquet(f"{sf}/documents.parquet").limit(150).collect()]
    for text in texts:
        words = [w.decode() for w in C.ascii_words(text.encode())]
        norm, placed = f" {' '.join(words)} ", "".join(f" {w}_{i}" for i, w in enumerate(words))
        for _, label, _, word, rare, p in L.RULES:
            if re.search(p, placed):
                assert rare in norm and any(x in norm for x in L.NEEDED[word, p]) and any(x in norm for x in L.ANY), (label, p, text)
        for p, _ in L.BASE:
            if re.search(L.numbered(p), placed):
                assert any(x in norm for x in L.ANY)
