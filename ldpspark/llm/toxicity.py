"""Toxicity by maximum-scoring segments of token log-odds.

Words get the log-odds of the toxic against the other training texts, each with a Dirichlet prior of the pooled counts;
texts count a word once. Every counted word scores its log-odds, shrunk by the share of their square that sampling alone
would give, (``SHRINK`` standard errors)^2, so common words that lean to the other texts lower a passage as telling ones raise
it; a small constant cost of each word keeps the expected score negative. Stems (the first letters of longer words) are
counted like words; a word without a score of its own takes that of its longest stem, so unseen endings count too. One
linear scan finds all maximal segments (no part that could be cut off or joined raises them).

The score S of a segment in a text of n words is held against the extreme-value law of chance maxima: with lambda the
positive root of E[exp(lambda * score)] = 1 under the non-toxic word frequencies, and K from the largest segments of the
non-toxic training texts (the mean of lambda * S - ln(K * n) is Euler's constant), lambda * S - ln(K * n) is its excess;
segments with a positive excess, an expected number below one in such a text, are the toxic passages. A logistic curve,
fitted on the training rows, turns the sum of the excesses into the score of the text.

Training uses a bounded sample: of each label, ``per_label`` rows on average, drawn by a keyed hash of the id, equal texts
once. The model sent to all tasks holds the words that score beyond the cost, at most ``table_words``, the largest z first.

Defined results: null and empty texts have no passage and get the score of texts without one; without training rows of
both labels every score is 0; rows with equal ids are judged one by one, and learn from all labels of their id.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

PER_LABEL, TABLE_WORDS, SEED = 12_000, 500_000, 5
PRIOR_SHARE, SHRINK, COST, DEFAULT_K = 0.2, 2.0, 0.3, 0.1
#: Bytes of the stems, longest first, up to a letter's end; a stem's key ends in a mark that no word has.
STEMS, MARK, KEPT_WORDS = (6, 5, 4), b"*", 300_000


def stem(word: bytes, size: int) -> bytes | None:
    """Key of the first ``size`` bytes of a longer word, and those of a letter begun in them."""
    while size < len(word) and word[size] & 0xC0 == 0x80:
        size += 1
    return word[:size] + MARK if size < len(word) else None


@dataclass
class Model:
    words: dict[bytes, float] = field(default_factory=dict)
    lam: float = 1.0
    k: float = DEFAULT_K
    intercept: float = 0.0
    slope: float = 0.0
    ready: bool = False
    cost: float = COST

    def __post_init__(self) -> None:
        self.seen: dict[bytes, float | None] = {}

    def __getstate__(self) -> dict:
        return self.__dict__ | {"seen": {}}

    def values(self, words: list[bytes]) -> list[float | None]:
        """Log-odds of each word, or None; what a word has is kept for its next places."""
        seen = self.seen
        out = list(map(seen.get, words, repeat(False)))
        if False in out:
            if len(seen) > KEPT_WORDS:
                seen.clear()
            table = self.words
            for w in {w for w, x in zip(words, out, strict=True) if x is False}:
                x = table.get(w)
                if x is None:
                    x = next((table[k] for n in STEMS if (k := stem(w, n)) in table), None)
                seen[w] = x
            out = list(map(seen.get, words))
        return out

    def excess(self, score: float, n: int) -> float:
        return self.lam * score - math.log(max(self.k * n, 1.0))

    def segments(self, text: bytes | None) -> tuple[int, list[tuple[int, int, float]]]:
        """Number of words; (first word, last word, score) of each maximal segment, in order."""
        words = C.ascii_words(text)
        if not self.words:
            return len(words), []
        cost = self.cost
        hits = [(i, s - cost) for i, s in enumerate(self.values(words)) if s is not None]
        return len(words), segments(hits, cost) if any(s > 0 for _, s in hits) else []

    def passages(self, text: bytes | None) -> tuple[int, list[tuple[int, int, float, float]]]:
        """Number of words; (first word, last word, score, excess) of each toxic passage, in order."""
        n, found = self.segments(text)
        return n, [(a, b, s, x) for a, b, s in found if (x := self.excess(s, n)) > 0]

    def probability(self, total: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.intercept + self.slope * total))) if self.ready else np.zeros(len(total))


def segments(hits: list[tuple[int, float]], cost: float) -> list[tuple[int, int, float]]:
    """All maximal segments (first, last, score) of a text in which the places ``hits`` score and all others cost.

    Candidates are kept with the sums before and after them; each new hit is joined to the last candidate with a smaller
    sum before it, if its own sum exceeds that one's. Every hit enters and leaves the list once.
    """
    held: list[tuple[int, int, float, float]] = []
    total, at = 0.0, 0
    for place, score in hits:
        total -= cost * (place - at)
        at = place + 1
        before, total = total, total + score
        if score <= 0:
            continue
        new = (place, place, before, total)
        while True:
            k = len(held) - 1
            while k >= 0 and held[k][2] >= new[2]:
                k -= 1
            if k < 0 or held[k][3] >= new[3]:
                held.append(new)
                break
            new = (held[k][0], new[1], held[k][2], new[3])
            del held[k:]
    return [(a, b, after - before) for a, b, before, after in held]


def features(text: bytes | None) -> set[bytes]:
    """Distinct words and stems of a text."""
    words = set(C.ascii_words(text))
    return words.union({k for w in words for n in STEMS if (k := stem(w, n))})


def decay(scores: np.ndarray, shares: np.ndarray, cost: float) -> float:
    """Root lambda > 0 of the mean of exp(lambda * score) = 1, words outside the table scoring -cost."""
    rest = 1 - shares.sum()

    def mean(x: float) -> float:
        return float((shares * np.exp(np.minimum(x * scores, 700))).sum() + rest * math.exp(-x * cost)) - 1

    lo, hi = 0.0, 1e-3
    while mean(hi) < 0 and hi < 50:
        lo, hi = hi, hi * 2
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if mean(mid) < 0 else (lo, mid)
    return max(hi, 1e-3)


def logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Intercept and slope (not negative) by Newton steps with a small ridge."""
    a, b = math.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)), 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a + b * x, -35, 35)))
        w = p * (1 - p)
        g = np.array([(y - p).sum() - 1e-3 * a, ((y - p) * x).sum() - 1e-1 * b])
        h = np.array([[w.sum() + 1e-3, (w * x).sum()], [(w * x).sum(), (w * x * x).sum() + 1e-1]])
        d = np.linalg.solve(h, g)
        d *= min(1.0, 2.0 / max(abs(d).max(), 1e-12))
        a, b = a + d[0], b + d[1]
        if abs(d).max() < 1e-8:
            break
    return float(a), float(max(b, 0.0))


def fit(
    docs: DataFrame, labels: DataFrame, *, id_col: str, text_col: str, label_col: str, train: Column | None, per_label: int, table_words: int, seed: int,
) -> Model:
    """Words, extreme-value parameters and curve. The driver holds the standing-out words and one number a sampled row."""
    known = labels.select(F.col(id_col).alias("l_id"), F.col(label_col).cast("int").alias("label")).filter("label is not null and l_id is not null")
    known = known if train is None else known.filter(train)
    sizes = {r[0]: r[1] for r in known.groupBy("label").count().collect()}
    model = Model()
    if not sizes.get(0) or not sizes.get(1):
        return model
    share = F.when(F.col("label") == 1, min(1.0, per_label / sizes[1])).otherwise(min(1.0, per_label / sizes[0]))
    drawn = known.filter((C.uniform(F.lit("toxic"), F.lit(seed), F.col("l_id")) < share) & F.col("label").isin(0, 1))
    drawn = C.small(C.stored(drawn, "labels"), 4 * per_label)
    rows = docs.select(F.col(id_col).alias("d_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    sample = rows.join(drawn, F.col("d_id") == F.col("l_id")).select("text", "label")
    sample = C.stored(sample.groupBy(F.xxhash64("text").alias("th"), "label").agg(F.first("text").alias("text")), "toxic-sample")

    def count(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("toxicity", lambda: None)
        seen: tuple[Counter, Counter] = (Counter(), Counter())
        for batch in stream:
            for label, text in zip(batch.column(0).to_pylist(), C.binary_list(batch.column(1)), strict=True):
                seen[label].update(features(text))
        words = list(seen[0].keys() | seen[1].keys())
        for lo in range(0, len(words), 50_000):
            w = words[lo : lo + 50_000]
            yield pa.RecordBatch.from_pydict({"word": pa.array(w, pa.binary()), "t": pa.array([seen[1][x] for x in w], pa.int64()), "o": pa.array([seen[0][x] for x in w], pa.int64())})

    counted = C.stored(sample.select("label", "text").mapInArrow(count, "word binary, t bigint, o bigint").groupBy("word").agg(F.sum("t").alias("t"), F.sum("o").alias("o")), "toxic-words")
    is_word = F.substring("word", -1, 1) != F.lit(MARK)
    nt, no, nw, ow = counted.agg(F.sum("t"), F.sum("o"), F.sum(F.when(is_word, F.col("t"))), F.sum(F.when(is_word, F.col("o")))).first()
    if not nt or not no:
        return model
    # only words that score reach the driver
    prior, a = PRIOR_SHARE * (nt + no), PRIOR_SHARE * (F.col("t") + F.col("o"))
    odds = F.log((F.col("t") + a) / F.greatest(nt + prior - F.col("t") - a, F.lit(1e-9))) - F.log((F.col("o") + a) / F.greatest(no + prior - F.col("o") - a, F.lit(1e-9)))
    z = odds / F.sqrt(1 / (F.col("t") + a) + 1 / (F.col("o") + a))
    share = F.when(is_word, (F.col("o") + a) / (ow + PRIOR_SHARE * (nw + ow))).otherwise(0.0)
    best = counted.select("word", odds.alias("odds"), z.alias("z"), share.alias("share")).filter((F.abs("z") > SHRINK))
    best = best.select("word", (F.col("odds") * (1 - SHRINK**2 / (F.col("z") * F.col("z")))).alias("score"), "z", "share")
    rows = best.orderBy(F.desc(F.abs("z")), "word").limit(table_words).collect()
    model.words = {bytes(r["word"]): r["score"] for r in rows}
    model.lam = decay(np.array([r["score"] for r in rows]) - model.cost, np.array([r["share"] for r in rows]), model.cost) if rows else 1.0
    model.k = _constant(sample, model)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def measure(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("toxicity", lambda: None)
        for batch in stream:
            own = [shared.value.passages(t) for t in C.binary_list(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([float(sum(p[3] for p in x)) for _, x in own])], ["label", "x"])

    found = np.array([tuple(r) for r in sample.select("label", "text").mapInArrow(measure, "label int, x double").toLocalIterator()], float)
    # the sample has the labels in other shares than the corpus: rows are weighted back through the intercept
    model.intercept, model.slope = logistic(found[:, 1], found[:, 0])
    kept = {k: (found[:, 0] == k).sum() / sizes[k] for k in (0, 1)}
    model.intercept -= math.log(max(kept[1], 1e-9) / max(kept[0], 1e-9))
    model.ready = True
    return model


def _constant(sample: DataFrame, model: Model) -> float:
    """K of the extreme-value law: the largest segments of the non-toxic texts follow it on average."""
    shared = sample.sparkSession.sparkContext.broadcast(model)

    def largest(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("toxicity", lambda: None)
        for batch in stream:
            found = [shared.value.segments(t) for t in C.binary_list(batch.column(0))]
            x = [shared.value.lam * max((s for _, _, s in own), default=0.0) - math.log(n) for n, own in found if n]
            yield pa.RecordBatch.from_pydict({"x": pa.array(x, pa.float64())})

    mean = sample.filter("label = 0").select("text").mapInArrow(largest, "x double").agg(F.avg("x")).first()[0]
    return DEFAULT_K if mean is None else math.exp(min(mean - np.euler_gamma, 0.0))


def toxicity(
    docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", train: Column | None = None,
    per_label: int = PER_LABEL, table_words: int = TABLE_WORDS, seed: int = SEED,
) -> DataFrame:
    """id, score and passages (first and last word, score, excess) of every row. ``train``: a condition on ``l_id``."""
    model = fit(docs, labels, id_col=id_col, text_col=text_col, label_col=label_col, train=train, per_label=per_label, table_words=table_words, seed=seed)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = pa.list_(pa.struct([("first", pa.int64()), ("last", pa.int64()), ("score", pa.float64()), ("excess", pa.float64())]))

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("toxicity", lambda: None)
        model = shared.value
        for batch in stream:
            found = [model.passages(t)[1] for t in C.binary_list(batch.column(1))]
            score = model.probability(np.array([sum(p[3] for p in x) for x in found], float))
            passages = [[dict(zip(("first", "last", "score", "excess"), p, strict=True)) for p in x] for x in found]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score, pa.float64()), pa.array(passages, kind)], [id_col, "score", "passages"])

    schema = f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, score double, passages array<struct<first:bigint,last:bigint,score:double,excess:double>>"
    return docs.select(id_col, text_col).mapInArrow(step, schema)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: learns labels of four folds of five, scores all."""
    found = toxicity(C.table(spark, sf_dir, "documents"), C.table(spark, sf_dir, "labels"), train=~C.held_out(F.col("l_id")))
    return found.select("doc_id", C.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
