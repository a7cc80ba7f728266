"""Language identification with hyperdimensional profiles.

Every letter has a random vector of +1 and -1. A letter trigram's vector is the product of its letters' vectors, the
first rotated twice, the second once. A language's prototype is the sum of the trigram vectors of its texts, a document's
vector the sum of its own; the prototype with the largest cosine wins. Word borders count as one more letter.

As a document's product with a prototype is the sum over its trigrams of their products with it, those are put into one
table (alphabet^3 rows, a column a language) when the prototypes are ready; documents are scored by sums of its rows,
which are exactly the products of the vectors. The document's own vector is bundled for its length: a matrix product of the
trigram counts of some documents with the vectors of their trigrams. So the score is the cosine.

The alphabet holds the most frequent letters of the training texts and one sign for all others. Prototypes are fitted on
a bounded sample of the labelled rows, ``per_language`` rows of each language on average, drawn by a keyed hash of the id.

Defined results: null texts and texts without letters are ``und`` with score 0, as all texts are if there is nothing to
learn from; rows with equal ids are judged one by one; ties go to the language first in order.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

DIMENSIONS, ALPHABET, PER_LANGUAGE, SEED = 4096, 64, 1500, 11
UNKNOWN = "und"


def code_points(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased code points of all texts, each with a border before and after it, and where each text ends."""
    raw = [t.decode().lower() for t in texts]
    sizes = np.array([len(t) + 2 for t in raw])
    joined = "\0\0".join(raw)
    return np.frombuffer(f"\0{joined}\0".encode("utf-32-le", "surrogatepass"), np.uint32), np.cumsum(sizes)


_LETTER: np.ndarray | None = None


def letters() -> np.ndarray:
    """True for code points that are letters."""
    global _LETTER
    if _LETTER is None:
        _LETTER = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)
    return _LETTER


def symbols_of(common: list[int]) -> np.ndarray:
    """Symbol of each code point: 0 border, 1 any other letter, 2... the alphabet."""
    out = letters().astype(np.uint8)
    out[common] = np.arange(2, 2 + len(common))
    return out


def trigrams(texts: list[bytes], symbol: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Trigram numbers of all texts, one after the other, and where each text's end. Runs of borders count once."""
    points, ends = code_points(texts)
    s = symbol[points]
    keep = np.ones(len(s), bool)
    keep[1:] = (s[1:] != 0) | (s[:-1] != 0)
    keep[ends[:-1]] = True
    kept_ends = np.cumsum(keep)[ends - 1] if len(ends) else ends
    s = s[keep].astype(np.int32)
    if len(s) < 3:
        return np.zeros(0, np.int32), np.zeros(len(texts), np.int64)
    code = (s[:-2] * size + s[1:-1]) * size + s[2:]
    # a trigram must not span two texts, nor have its border in the middle
    valid = s[1:-1] != 0
    cross = np.concatenate([kept_ends[:-1] - 1, kept_ends[:-1] - 2])
    valid[cross[(cross >= 0) & (cross < len(valid))]] = False
    stop = np.concatenate(([0], np.cumsum(valid)))[np.maximum(kept_ends - 2, 0)]
    return code[valid], stop


def bind(size: int, dimensions: int, seed: int) -> np.ndarray:
    """Random sign vectors of the symbols."""
    return np.where(np.random.default_rng(seed).random((size, dimensions)) < 0.5, np.float32(-1), np.float32(1))


def bundle(codes: np.ndarray, counts: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Sum of the trigram vectors, as whole numbers."""
    size, out = len(vectors), np.zeros(vectors.shape[1], np.float64)
    first, second = np.roll(vectors, 2, axis=1), np.roll(vectors, 1, axis=1)
    for lo in range(0, len(codes), 256):
        c = codes[lo : lo + 256]
        out += counts[lo : lo + 256].astype(np.float64) @ (first[c // size // size] * second[c // size % size] * vectors[c % size])
    return out.astype(np.int64)


#: Documents, their trigrams, different trigrams and dimensions that are bundled at a time.
GROUP, GROUP_CODES, ROWS, PART = 64, 60_000, 1024, 512


def lengths(codes: np.ndarray, bounds: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Length of the bundled vector of each text; bounds: where the trigrams of each begin, and the end of the last."""
    out, lo, n = np.zeros(len(bounds) - 1), 0, len(bounds) - 1
    size, shifted = len(vectors), (np.roll(vectors, 2, axis=1), np.roll(vectors, 1, axis=1), vectors)
    while lo < n:
        hi = int(np.clip(np.searchsorted(bounds, bounds[lo] + GROUP_CODES, "right") - 1, lo + 1, min(n, lo + GROUP)))
        own, place = np.unique(codes[bounds[lo] : bounds[hi]], return_inverse=True)
        if not len(own):
            lo = hi
            continue
        text = np.repeat(np.arange(hi - lo), np.diff(bounds[lo : hi + 1]))
        counts = np.bincount(text * len(own) + place, minlength=(hi - lo) * len(own)).reshape(hi - lo, -1)
        counts = counts.astype(np.float32 if bounds[hi] - bounds[lo] < 1 << 24 else np.float64)
        letter = (own // size // size, own // size % size, own % size)
        for k in range(0, vectors.shape[1], PART):
            parts = [x[:, k : k + PART] for x in shifted]
            bundled = sum(counts[:, u : u + ROWS] @ (parts[0][letter[0][u : u + ROWS]] * parts[1][letter[1][u : u + ROWS]] * parts[2][letter[2][u : u + ROWS]]) for u in range(0, len(own), ROWS))
            out[lo:hi] += (bundled.astype(np.float64) ** 2).sum(axis=1)
        lo = hi
    return np.sqrt(out)


@dataclass
class Model:
    languages: list[str]
    alphabet: list[int]
    size: int
    dimensions: int
    #: products of all trigram vectors with the prototypes of length one
    table: np.ndarray
    seed: int = SEED

    def score(self, texts: list[bytes]) -> tuple[list[str], np.ndarray]:
        """Language and cosine (0 at least) of each text."""
        out, cosines = [UNKNOWN] * len(texts), np.zeros(len(texts))
        if not self.languages or not texts:
            return out, cosines
        symbol = _symbols(tuple(self.alphabet))
        codes, stop = trigrams(texts, symbol, self.size)
        sums = np.zeros((len(texts), len(self.languages)))
        full = np.flatnonzero(np.diff(stop, prepend=0))
        start = np.concatenate(([0], stop[:-1]))[full] if len(full) else full
        if not len(full):
            return out, cosines
        for k in range(len(self.languages)):
            sums[full, k] = np.add.reduceat(self.table[k][codes], start, dtype=np.float64)
        best = sums.argmax(axis=1)
        # trigrams of texts without any take no room, so each text's end where the next one's begin
        length = lengths(codes, np.append(start, stop[-1]), _vectors(self.size, self.dimensions, self.seed))
        for i, own in zip(full.tolist(), length.tolist(), strict=True):
            out[i] = self.languages[best[i]]
            cosines[i] = min(1.0, max(0.0, sums[i, best[i]] / own)) if own else 0.0
        return out, cosines


@lru_cache(maxsize=1)
def _vectors(size: int, dimensions: int, seed: int) -> np.ndarray:
    return bind(size, dimensions, seed)


_SYMBOLS: dict[tuple, np.ndarray] = {}


def _clear() -> None:
    _SYMBOLS.clear()
    _vectors.cache_clear()


def _symbols(alphabet: tuple) -> np.ndarray:
    if alphabet not in _SYMBOLS:
        _SYMBOLS.clear()
        _SYMBOLS[alphabet] = symbols_of(list(alphabet))
    return _SYMBOLS[alphabet]


def pieces(texts: list[bytes | None], most: int = 1 << 18) -> Iterator[tuple[int, int]]:
    """Bounds of consecutive texts of about ``most`` bytes together."""
    lo = total = 0
    for k, t in enumerate(texts):
        total += len(t or b"")
        if total >= most:
            yield lo, k + 1
            lo, total = k + 1, 0
    if lo < len(texts):
        yield lo, len(texts)


def fit(labelled: DataFrame, *, id_col: str, text_col: str, lang_col: str, per_language: int, alphabet: int, dimensions: int, seed: int) -> Model:
    """Prototypes of the languages in ``labelled``. The driver holds letter counts and one vector a language."""
    spark = labelled.sparkSession
    labelled = labelled.select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    counts = {r[0]: r[1] for r in labelled.groupBy("lang").count().toLocalIterator()}
    languages = sorted(counts)
    if not languages:
        return Model([], [], alphabet, dimensions, np.zeros((0, 0), np.float32))
    share = spark.createDataFrame([(x, min(1.0, per_language / counts[x])) for x in languages], "l string, share double")
    drawn = labelled.join(F.broadcast(share), F.col("lang") == F.col("l")).filter(C.uniform(F.lit("lang"), F.lit(seed), F.col("id")) < F.col("share"))
    drawn = C.stored(drawn.select("lang", "text"), "language-sample")

    def count(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("language", _clear)
        total: Counter = Counter()
        for batch in stream:
            for t in C.binary_list(batch.column(1)):
                total.update(t.decode().lower())
        seen = [(ord(c), n) for c, n in total.items() if c.isalpha()]
        yield pa.RecordBatch.from_pydict({"letter": pa.array([x[0] for x in seen], pa.int32()), "n": pa.array([x[1] for x in seen], pa.int64())})

    letters_seen = drawn.mapInArrow(count, "letter int, n bigint").groupBy("letter").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "letter").limit(alphabet - 2)
    common = sorted(r[0] for r in letters_seen.collect())

    def profile(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("language", _clear)
        symbol, vectors = symbols_of(common), bind(alphabet, dimensions, seed)
        held: dict[str, np.ndarray] = {}
        for batch in stream:
            langs, texts = np.array(batch.column(0).to_pylist(), object), C.binary_list(batch.column(1))
            for lang in set(langs.tolist()):
                own = [texts[i] for i in np.flatnonzero(langs == lang)]
                for lo, hi in pieces(own):
                    codes, _ = trigrams(own[lo:hi], symbol, alphabet)
                    held.setdefault(lang, np.zeros(alphabet**3, np.int64))[:] += np.bincount(codes, minlength=alphabet**3)
        for lang, n in held.items():
            codes = np.flatnonzero(n)
            yield pa.RecordBatch.from_pydict({"lang": [lang], "vector": pa.array([bundle(codes, n[codes], vectors).tolist()], pa.list_(pa.int64()))})

    prototype = {x: np.zeros(dimensions, np.int64) for x in languages}
    for row in drawn.mapInArrow(profile, "lang string, vector array<bigint>").toLocalIterator():
        prototype[row[0]] += np.array(row[1])
    return Model(languages, common, alphabet, dimensions, product_table(np.array([prototype[x] for x in languages]), bind(alphabet, dimensions, seed)), seed)


def product_table(prototypes: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Language x trigram: product of the trigram's vector with the language's prototype of length one."""
    length = np.sqrt((prototypes.astype(np.float64) ** 2).sum(axis=1, keepdims=True))
    unit = (prototypes / np.maximum(length, 1e-12)).astype(np.float32)
    first, second, size = np.roll(vectors, 2, axis=1), np.roll(vectors, 1, axis=1), len(vectors)
    out = np.zeros((len(unit), size, size, size), np.float32)
    for k, p in enumerate(unit):
        for a in range(size):
            out[k, a] = (second * (first[a] * p)) @ vectors.T
    return out.reshape(len(unit), -1)


def identify(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", train: Column | None = None, keep: float | None = None,
    per_language: int = PER_LANGUAGE, alphabet: int = ALPHABET, dimensions: int = DIMENSIONS, seed: int = SEED,
) -> DataFrame:
    """id, lang_pred, score of every row, learnt from its rows with a language for which ``train`` holds (all, if none).

    With ``keep``, instead: the rows (all columns) that have a language and a score of at least ``keep``.
    """
    labelled = docs.filter(F.col(lang_col).isNotNull() & (F.lit(True) if train is None else train))
    model = fit(labelled, id_col=id_col, text_col=text_col, lang_col=lang_col, per_language=per_language, alphabet=alphabet, dimensions=dimensions, seed=seed)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    where = docs.columns.index(text_col) if keep is not None else 1

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("language", _clear)
        for batch in stream:
            texts, found, scores = C.binary_list(batch.column(where)), [], [np.zeros(0)]
            for lo, hi in pieces(texts):
                langs, cosines = shared.value.score([t or b"" for t in texts[lo:hi]])
                found += langs
                scores.append(cosines)
            score = np.concatenate(scores)
            if keep is None:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.string()), pa.array(score)], [id_col, "lang_pred", "score"])
            else:
                yield batch.filter(pa.array([x != UNKNOWN and s >= keep for x, s in zip(found, score, strict=True)], pa.bool_()))

    if keep is not None:
        return docs.mapInArrow(step, docs.schema)
    return docs.select(id_col, text_col).mapInArrow(step, f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, lang_pred string, score double")


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: learns from four folds of five, judges all."""
    docs = C.table(spark, sf_dir, "documents")
    found = identify(docs, train=~C.held_out(F.col("doc_id")))
    return found.select("doc_id", C.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
