"""Cleaning doesn't depend on how the benchmark is cut into slices."""

import pytest

from ldpspark.llm import decontaminate

ITEMS = [" ".join(f"{x}{i}" for i in range(13)) for x in "abc"]


@pytest.mark.parametrize("remove", ["documents", "spans"])
def test_slices_are_judged_together(spark, remove):
    filler = lambda n, k: " ".join(f"f{k}x{i}" for i in range(n))
    docs = [
        (1, f"{filler(200, 1)}, {ITEMS[0]}! {filler(200, 2)} {ITEMS[1]} end"),  # 3 % in each of two slices
        (2, f"{filler(400, 3)} {ITEMS[2]}"), (3, ITEMS[0]), (3, ITEMS[0]), (4, f"{ITEMS[0]} {ITEMS[1]} {ITEMS[2]}"), (5, filler(20, 4)), (6, None), (7, ""),
        (None, f"x {ITEMS[1]} y"),
    ]
    df = spark.createDataFrame([(b"k", i, t, [1], None) for i, t in docs], "Hits binary, doc_id long, text string, items array<int>, _hits string")
    bench = spark.createDataFrame(list(enumerate(ITEMS)), "item_id long, text string")
    got = {}
    for limit in (decontaminate.SLICE_BYTES, 60, 1):
        out = decontaminate.clean(df, bench, remove=remove, slice_bytes=limit)
        assert out.columns == df.columns
        got[limit] = sorted(map(repr, out.collect()))
    assert got[1] == got[60] == got[decontaminate.SLICE_BYTES]
    texts = [r["text"] for r in out.collect() if r["doc_id"] == 1]
    assert texts == ([] if remove == "documents" else [f"{filler(200, 1)},  ! {filler(200, 2)}   end"])
