"""Benchmark decontamination: a broadcast hash set of normalised test n-grams against token windows of documents.

Words are lower-cased runs of letters and digits (every non-ASCII byte counts as a letter). A window is ``n``
consecutive words of a benchmark item; an item with fewer words, but at least one, is one window of its length.
Word hashes are sums over bytes, window hashes differences of running sums over word hashes; a document window whose hash is
in the sorted hash set is verified by the words themselves.

Defined results: null and empty texts have no words and are clean; null items and items without words have no window;
a null item id counts as the empty text; repeated rows are judged one by one; an empty benchmark leaves all clean.

The index of the benchmark goes to every task. It is made of flat arrays, at most ``INDEX_BYTES`` for each byte of benchmark
text, and bounded by ``slice_bytes`` of that: a larger benchmark is taken in slices (an item longer than that in overlapping
parts), one pass over the documents each, the hit words being kept as a bit map between passes.
"""

from __future__ import annotations

import itertools
import re
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import BinaryType, StructField, StructType

from . import common as C
from .words import M1, SEGMENT, word_hashes

SLICE_BYTES = 16 << 20
#: One window has 20 bytes of arrays and its word at least two of text; a text is held once more.
INDEX_BYTES = 11
#: Words of a document whose windows are hashed at a time.
CHUNK = 1 << 16
STEP = np.uint64(0xD1342543DE82EF95)
WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


@lru_cache(maxsize=1)
def _powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    odd = int(STEP)
    return np.cumprod(np.full(size, odd, np.uint64)), np.cumprod(np.full(size, pow(odd, -1, 1 << 64), np.uint64))


def window_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """Hash of each run of ``size`` words: differences of a running sum of mixed word hashes times powers of an odd number."""
    if len(words) < size:
        return words[:0]
    mixed = (words ^ (words >> np.uint64(29))) * M1
    n = len(words)
    power, inverse = _powers(max(CHUNK + 64, n))
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(mixed * power[:n], out=total[1:])
    h = (total[size:] - total[:-size]) * inverse[: n - size + 1]
    return h ^ (h >> np.uint64(32))


class Windows:
    """The windows of one length of some items: sorted hashes with the item and the place in the words' text of each."""

    def __init__(self, items: list[tuple[int, bytes]], size: int):
        self.size, self.text = size, b" ".join(t for _, t in items)
        words, starts = word_hashes(self.text)
        owner = np.repeat(np.array([k for k, _ in items], np.int32), [t.count(b" ") + 1 for _, t in items])
        part = np.repeat(np.arange(len(items), dtype=np.int32), [t.count(b" ") + 1 for _, t in items])
        at = np.flatnonzero(part[size - 1 :] == part[: len(part) - size + 1])
        h = np.concatenate([window_hashes(words[lo : lo + CHUNK + size - 1], size) for lo in range(0, len(words) - size + 1, CHUNK)])[at]
        order = np.lexsort((owner[at], h))
        h, at = h[order], at[order]
        # an item holds a window once
        first = np.ones(len(h), bool)
        first[1:] = (h[1:] != h[:-1]) | (owner[at][1:] != owner[at][:-1])
        again = np.flatnonzero(~first)
        for j in range(size):
            first[again] |= words[at[again] + j] != words[at[again - 1] + j]
        self.hashes, at = h[first], at[first]
        self.owner, self.lo = owner[at], starts[at].astype(np.int32)
        self.hi = np.append(starts[1:] - 1, len(self.text))[at + size - 1].astype(np.int32)
        self.bits = max(16, min(25, len(self.hashes).bit_length() + 3))
        self.seen: np.ndarray | None = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"seen": None}

    def places(self, hashes: np.ndarray) -> np.ndarray:
        """Where hashes are those of a window; a table of their first bits passes few others on to the search."""
        if self.seen is None:
            self.seen = np.zeros(1 << self.bits, bool)
            self.seen[self.hashes >> np.uint64(64 - self.bits)] = True
        at = np.flatnonzero(self.seen[hashes >> np.uint64(64 - self.bits)])
        near = np.minimum(np.searchsorted(self.hashes, hashes[at]), len(self.hashes) - 1)
        return at[self.hashes[near] == hashes[at]]

    def owners(self, code: np.uint64, words: bytes) -> set[int]:
        """Items with a window of this hash and these words (joined by blanks)."""
        lo, hi = np.searchsorted(self.hashes, code), np.searchsorted(self.hashes, code, "right")
        return {int(self.owner[k]) for k in range(lo, hi) if self.text[self.lo[k] : self.hi[k]] == words}


class Index:
    """Windows of some benchmark items, by length."""

    def __init__(self, items: Iterable[tuple[object, str | None]], n: int = 13):
        self.names: list[str] = []
        held: dict[int, list[tuple[int, bytes]]] = {}
        for name, text in items:
            words = C.ascii_words((text or "").encode())
            if words:
                held.setdefault(min(n, len(words)), []).append((len(self.names), b" ".join(words)))
                self.names.append("" if name is None else str(name))
        self.windows = [Windows(x, size) for size, x in sorted(held.items())]

    def nbytes(self) -> int:
        return sum(len(w.text) + sum(x.nbytes for x in (w.hashes, w.owner, w.lo, w.hi)) for w in self.windows)


def scan_texts(index: Index, texts: list[bytes | None]) -> list[tuple[np.ndarray, set[int]]]:
    """For each text: mask over its words, and the numbers of items that occur. Texts are joined in blocks."""
    out: list[tuple[np.ndarray, set[int]]] = []
    lo = size = 0
    for k, text in enumerate(texts):
        size += len(text or b"")
        if size >= SEGMENT or k + 1 == len(texts):
            out += _scan_block(index, [t or b"" for t in texts[lo : k + 1]])
            lo, size = k + 1, 0
    return out


def _scan_block(index: Index, texts: list[bytes]) -> list[tuple[np.ndarray, set[int]]]:
    block = b"\n".join(texts).translate(C.WORD_TABLE)
    words, starts = word_hashes(block)
    bounds = np.searchsorted(starts, np.cumsum([0, *(len(t) + 1 for t in texts)]))
    hit = np.zeros(len(words) + 1, np.int32)
    items: list[set[int]] = [set() for _ in texts]
    for w in index.windows:
        known: dict[tuple[int, bytes], set[int]] = {}
        for lo in range(0, len(words) - w.size + 1, CHUNK):
            codes = window_hashes(words[lo : lo + CHUNK + w.size - 1], w.size)
            for i in w.places(codes).tolist():
                at = lo + i
                k = int(np.searchsorted(bounds, at, "right")) - 1
                if at + w.size > bounds[k + 1]:
                    continue  # across two texts
                end = starts[at + w.size] if at + w.size < len(starts) else len(block)
                own = b" ".join(block[starts[at] : end].split())
                key = (int(codes[i]), own)
                if key not in known:
                    known[key] = w.owners(codes[i], own)
                if known[key]:
                    hit[at] += 1
                    hit[at + w.size] -= 1
                    items[k] |= known[key]
    mask = np.cumsum(hit[:-1]) > 0
    return [(mask[a:b], x) for a, b, x in zip(bounds[:-1].tolist(), bounds[1:].tolist(), items, strict=True)]


def slices(benchmark: DataFrame, item_col: str, text_col: str, slice_bytes: int, n: int) -> Iterator[list[tuple[object, str]]]:
    """Items in lists of at most ``slice_bytes`` of text; the driver holds one list at a time.

    A longer item is cut into parts that share ``n`` - 1 words, so that each of its windows is whole in one.
    """
    held, size = [], 0
    for row in benchmark.select(item_col, text_col).toLocalIterator():
        for part, own in _parts(row[1] or "", slice_bytes, n):
            if held and size + own > slice_bytes:
                yield held
                held, size = [], 0
            held.append((row[0], part))
            size += own
    yield held


def _parts(text: str, most: int, n: int) -> Iterator[tuple[str, int]]:
    raw = text.encode()
    if len(raw) <= most:
        if raw:
            yield text, len(raw)
        return
    words = C.ascii_words(raw)
    lo = 0
    while lo == 0 or lo + n - 1 < len(words):
        hi, size = min(lo + n, len(words)), sum(len(w) + 1 for w in words[lo : lo + n])
        while hi < len(words) and size + len(words[hi]) < most:
            size += len(words[hi]) + 1
            hi += 1
        yield b" ".join(words[lo:hi]).decode(), size
        if hi == len(words):
            return
        lo = hi - n + 1


def contamination(
    docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id",
    item_text_col: str = "text", n: int = 13, slice_bytes: int = SLICE_BYTES,
) -> DataFrame:
    """One row per document: id, n_words, n_hit, items (sorted distinct ids as text)."""
    id_type = docs.schema[id_col].dataType.simpleString()
    schema = f"`{id_col}` {id_type}, n_words bigint, n_hit bigint, items array<string>"
    parts = slices(benchmark, item_col, item_text_col, slice_bytes, n)
    first, second = next(parts), next(parts, None)
    if second is None:
        index = Index(first, n)
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def one(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = shared.value
            for batch in stream:
                found = scan_texts(index, C.binary_list(batch.column(1)))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0), pa.array([len(m) for m, _ in found], pa.int64()), pa.array([int(m.sum()) for m, _ in found], pa.int64()),
                        pa.array([sorted({index.names[k] for k in items}) for _, items in found], pa.list_(pa.string())),
                    ], [id_col, "n_words", "n_hit", "items"],
                )

        return C.batches(docs.select(id_col, text_col), one, schema)

    held = docs.select(id_col, text_col)
    for k, items in enumerate(itertools.chain([first, second], parts)):
        held = C.stored(_pass(held, id_col, text_col, id_type, Index(items, n), first=k == 0), "windows")

    def last(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in stream:
            hits = [int(np.unpackbits(np.frombuffer(b, np.uint8)).sum()) for b in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(hits, pa.int64()), batch.column(3)], [id_col, "n_words", "n_hit", "items"]
            )

    return C.batches(held.select(id_col, "n_words", "hits", "items"), last, schema)


def _pass(held: DataFrame, id_col: str, text_col: str, id_type: str, index: Index, first: bool) -> DataFrame:
    """Adds one slice's hits to the bit maps and item lists."""
    shared = held.sparkSession.sparkContext.broadcast(index)

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = shared.value
        for batch in stream:
            found = scan_texts(index, C.binary_list(batch.column(1)))
            bits = [np.packbits(m) for m, _ in found]
            items = [{index.names[k] for k in x} for _, x in found]
            if not first:
                bits = [b | np.frombuffer(o, np.uint8) for b, o in zip(bits, batch.column(3).to_pylist(), strict=True)]
                items = [x | set(o) for x, o in zip(items, batch.column(4).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0), batch.column(1), pa.array([len(m) for m, _ in found], pa.int64()),
                    pa.array([b.tobytes() for b in bits], pa.binary()), pa.array([sorted(x) for x in items], pa.list_(pa.string())),
                ], [id_col, text_col, "n_words", "hits", "items"],
            )

    return C.batches(held, step, f"`{id_col}` {id_type}, `{text_col}` string, n_words bigint, hits binary, items array<string>")


def cut(text: bytes, mask: np.ndarray) -> bytes:
    """``text`` without its hit words; each removed run with what stands between its words becomes one blank."""
    out, last, spans = [], 0, [m.span() for m in WORD.finditer(text)]
    at = 0
    while at < len(spans):
        if mask[at]:
            end = at
            while end + 1 < len(spans) and mask[end + 1]:
                end += 1
            out += [text[last : spans[at][0]], b" "]
            last, at = spans[end][1], end
        at += 1
    return b"".join([*out, text[last:]])


def clean(
    docs: DataFrame, benchmark: DataFrame, *, remove: str = "documents", text_col: str = "text", item_col: str = "item_id",
    item_text_col: str = "text", n: int = 13, share: tuple[int, int] = (1, 20), slice_bytes: int = SLICE_BYTES,
) -> DataFrame:
    """``docs`` (all columns) without contaminated documents, or with the hit spans cut out (``remove="spans"``).

    A document is contaminated when it has a hit word and hit words are at least ``share`` of its words. With a benchmark
    over ``slice_bytes`` the hits of all slices are gathered first, so the outcome doesn't depend on the slices.
    """
    where = docs.columns.index(text_col)
    parts = slices(benchmark, item_col, item_text_col, slice_bytes, n)
    first, second = next(parts), next(parts, None)

    def cleaned(batch: pa.RecordBatch, texts: list[bytes | None], masks: list[np.ndarray]) -> pa.RecordBatch:
        bad = [bool(h) and share[1] * h >= share[0] * len(m) for m, h in ((m, int(m.sum())) for m in masks)]
        if remove == "documents":
            return batch.filter(pa.array([not x for x in bad], pa.bool_()))
        new = [cut(t, m).decode() if x else None if t is None else t.decode() for t, x, m in zip(texts, bad, masks, strict=True)]
        columns = batch.columns
        columns[where] = pa.array(new, batch.schema.field(where).type)
        return pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    if second is None:
        shared = docs.sparkSession.sparkContext.broadcast(Index(first, n))

        def one(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            C.own("decontamination", _powers.cache_clear)
            for batch in stream:
                texts = C.binary_list(batch.column(where))
                yield cleaned(batch, texts, [m for m, _ in scan_texts(shared.value, texts)])

        return docs.mapInArrow(one, docs.schema)

    hits = "hits"
    while hits in map(str.lower, docs.columns):
        hits = "_" + hits
    held = docs
    for items in itertools.chain([first, second], parts):
        held = C.stored(_marked(held, where, hits, Index(items, n)), "marked")

    def last(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("decontamination", _powers.cache_clear)
        for batch in stream:
            texts = C.binary_list(batch.column(where))
            masks = [np.unpackbits(np.frombuffer(b, np.uint8), count=len(C.ascii_words(t))) for t, b in zip(texts, batch.column(batch.num_columns - 1).to_pylist(), strict=True)]
            yield cleaned(pa.RecordBatch.from_arrays(batch.columns[:-1], schema=batch.schema.remove(batch.num_columns - 1)), texts, masks)

    return held.mapInArrow(last, docs.schema)


def _marked(held: DataFrame, where: int, hits: str, index: Index) -> DataFrame:
    """``held`` with one slice's hits added to the bit maps of its last column ``hits``, which the first slice makes."""
    shared = held.sparkSession.sparkContext.broadcast(index)
    first = held.columns[-1] != hits
    schema = StructType([*held.schema.fields, StructField(hits, BinaryType())]) if first else held.schema

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("decontamination", _powers.cache_clear)
        for batch in stream:
            bits = [np.packbits(m) for m, _ in scan_texts(shared.value, C.binary_list(batch.column(where)))]
            columns = batch.columns
            if not first:
                bits = [b | np.frombuffer(o, np.uint8) for b, o in zip(bits, columns.pop().to_pylist(), strict=True)]
            columns.append(pa.array([b.tobytes() for b in bits], pa.binary()))
            fields = list(batch.schema)[: len(columns) - 1]
            yield pa.RecordBatch.from_arrays(columns, schema=pa.schema([*fields, pa.field(hits, pa.binary())]))

    return held.mapInArrow(step, schema)


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract digest of :func:`contamination` over ``documents`` and ``benchmark``."""
    from pyspark.sql import functions as F

    found = contamination(C.table(spark, sf_dir, "documents"), C.table(spark, sf_dir, "benchmark"))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"),
    )


#: Windows as exact word lists; items shorter than 13 words join by their own length.
OP9_SQL = r"""
WITH w AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS words FROM documents),
b AS (SELECT item_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS words FROM benchmark),
bs AS (SELECT item_id, words, least(13, len(words)) AS size FROM b WHERE len(words) > 0),
bw AS (SELECT DISTINCT item_id, size, array_to_string(words[i:i + size - 1], ' ') AS gram FROM (SELECT *, unnest(generate_series(1, len(words) - size + 1)) AS i FROM bs)),
dw AS (SELECT doc_id, i, size, array_to_string(words[i:i + size - 1], ' ') AS gram FROM (SELECT doc_id, words, size, unnest(generate_series(1, len(words) - size + 1)) AS i FROM w, (SELECT DISTINCT size FROM bw) WHERE len(words) >= size)),
hits AS (SELECT dw.doc_id, dw.i, dw.size, bw.item_id FROM dw JOIN bw USING (size, gram)),
covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + size - 1)) AS p FROM (SELECT DISTINCT doc_id, i, size FROM hits)) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS names FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item_id FROM hits) GROUP BY doc_id)
SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(words) AS contaminated
FROM w LEFT JOIN covered USING (doc_id) LEFT JOIN items USING (doc_id)
"""
