"""MinHash near-dedup: bottom-k sketches from one hash function, inverted lists, union-sketch filter, exact Jaccard.

A document's set holds the 64-bit hashes of its distinct shingles of ``width`` words (all words at once, if fewer).
Documents of equal sets form a class (128-bit digest of the set); all that follows works on classes, so groups of exact
copies cost one row each. The sketch of a class is the ``k`` least hashes of its set.

Two sets of similarity t or more share at least ``c`` values in their sketches, but for a chance of ``miss`` (binomial
tail; for sets below k values the share is certain). So they share one of the ``k - c + 1`` values of either sketch that
the fewest sketches hold: only those enter the inverted lists. Values that many unlike texts share (common passages)
are last in that order and drop out; values of one class fill places without making a list.

Lists make links in two rounds. First the most central class of each list (largest product of its values' list sizes)
is paired with all others; pairs whose sizes allow the similarity and whose bottom-k sketch of the union shows enough
common values are decided on the full sets, built anew from both texts. This joins groups of copies by a linear number
of pairs. Where a list's classes are then still in different components, they are compared with each other: all lists
with the same central class form one group (so a class is in few groups, not in one for each value). A group is cut into
blocks of bounded size, each of one component or of several small ones, and dealt out in pairs of blocks that don't lie in
the same component; the full sets of its classes are built once, and a task finds all intersections of its two blocks' sets
by a product of their incidence matrices. It returns links that join components, a forest, not the pairs. No pair of a list
is left out. Values that very many classes hold are joined by broadcast; there are few of them by their count.

Defined results: null texts and texts without words have an empty set and are linked with nothing; rows with equal ids
are kept apart by their texts; a null id is left out of the least id of a component (a component of null ids has none).
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C
from .components import components
from .words import SEGMENT, _tables, word_hashes

K, MISS = 40, 1e-10
#: Classes and values of a block, columns of an incidence matrix at a time.
BLOCK, BLOCK_VALUES, COLUMNS, SLICE = 256, 400_000, 4096, 512
M1, M2, M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def _combined(words: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` words."""
    h = np.full(len(words) - width + 1, width, np.uint64)
    for j in range(width):
        h = (h ^ words[j : j + len(h)]) * M1
        h ^= h >> np.uint64(32)
    h = (h ^ (h >> np.uint64(30))) * M2
    h = (h ^ (h >> np.uint64(27))) * M3
    return h ^ (h >> np.uint64(31))


def shingle_sets(texts: list[bytes | None], width: int) -> Iterator[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's shingles, in order; texts are taken in blocks."""
    lo = size = 0
    for k, text in enumerate(texts):
        size += len(text or b"")
        if size < SEGMENT and k + 1 < len(texts):
            continue
        block = [t or b"" for t in texts[lo : k + 1]]
        words, starts = word_hashes(b"\n".join(block).lower())
        bounds = np.searchsorted(starts, np.cumsum([0, *(len(t) + 1 for t in block)]))
        every = _combined(words, width) if len(words) >= width else words[:0]
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            yield np.unique(every[a : b - width + 1]) if b - a >= width else _combined(words[a:b], b - a) if b > a else words[:0]
        lo, size = k + 1, 0


def digest(values: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(values.tobytes())


@lru_cache(maxsize=64)
def least_common(k: int, share: float, miss: float = MISS) -> int:
    """Largest c for which a binomial (k, share) is below c with a chance of at most ``miss``."""
    tail = 0.0
    for c in range(k + 1):
        tail += math.comb(k, c) * share**c * (1 - share) ** (k - c)
        if tail > miss:
            return max(1, c)
    return k


def _needed(n: Column, k: int, num: int, den: int) -> Column:
    """Common sketch values that a set of n values must have with a similar one."""
    return F.least(F.lit(least_common(k, num / den)).cast("long"), F.ceil(n * num / den)).cast("int")


def sketch(docs: DataFrame, *, id_col: str, text_col: str, width: int, k: int) -> DataFrame:
    """id, th (hash of the text), n (values of the set), cls (digest; null if empty), sketch, of every row."""
    id_type = docs.schema[id_col].dataType.simpleString()

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("near-duplicates", _tables.cache_clear)
        for batch in (whole.slice(lo, SLICE) for whole in stream for lo in range(0, whole.num_rows, SLICE)):
            sizes, classes, least = [], [], []
            for values in shingle_sets(C.binary_list(batch.column(2)), width):
                sizes.append(len(values))
                classes.append(digest(values) if len(values) else None)
                least.append((values[:k] >> np.uint64(1)).astype(np.int64))
            flat = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, least)]), pa.int32()), pa.array(np.concatenate(least) if least else [], pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sizes, pa.int64()), pa.array(classes, pa.binary()), flat], ["id", "th", "n", "cls", "sketch"])

    rows = docs.select(F.col(id_col).alias("id"), F.xxhash64(text_col).alias("th"), F.col(text_col).alias("text"))
    return rows.mapInArrow(step, f"id {id_type}, th bigint, n bigint, cls binary, sketch array<bigint>")


def _listed(classes: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """Classes that can have a partner, with ``prefix``: their values to be listed, rarest first, and ``central``."""
    values = classes.select("cls", F.explode("sketch").alias("v"))
    counts = C.stored(values.groupBy("v").agg(F.count("*").alias("held")).filter("held > 1"), "counts")
    shared = C.join_counted(values, counts, "v", "held").groupBy("cls").agg(F.sort_array(F.collect_list(F.struct("held", "v"))).alias("s"), F.sum(F.log2("held")).alias("central"))
    # values of one class alone are the rarest of all and take the first places
    both = shared.join(classes, "cls").withColumn("places", F.size("s") - _needed(F.col("n"), k, num, den) + 1)
    return both.filter("places > 0").select("cls", "id", "th", "n", "sketch", "central", F.transform(F.slice("s", F.lit(1), F.col("places")), lambda x: x["v"]).alias("prefix"))


def _may_match(k: int, num: int, den: int) -> Column:
    """Of two classes (columns of a and b): sizes allow the similarity and the union's sketch shows enough in common."""
    na, nb = F.col("a.n"), F.col("b.n")
    common = F.array_intersect("a.sketch", "b.sketch")
    union = F.slice(F.array_sort(F.array_union("a.sketch", "b.sketch")), 1, k)
    enough = F.greatest(_needed(na, k, num, den), _needed(nb, k, num, den))
    return (den * F.least(na, nb) >= num * F.greatest(na, nb)) & (F.size(common) >= enough) & (F.size(F.array_intersect(common, union)) >= enough)


def _verified(docs: DataFrame, pairs: DataFrame, *, id_col: str, text_col: str, width: int, num: int, den: int) -> DataFrame:
    """Pairs (a, b) of classes whose full sets are similar. pairs: a, a_id, a_th, b, b_id, b_th; one text a class."""
    ends = pairs.select(F.col("a").alias("cls"), F.col("a_id").alias("id"), F.col("a_th").alias("th")).union(pairs.select("b", "b_id", "b_th")).distinct()
    ends = C.small(C.stored(ends, "ends"))
    rows = docs.select(F.col(id_col).alias("d_id"), F.xxhash64(text_col).alias("d_th"), F.col(text_col).alias("text"))
    texts = C.stored(rows.join(ends, (F.col("d_th") == F.col("th")) & F.col("d_id").eqNullSafe(F.col("id"))).select("cls", "text"), "texts")
    joined = pairs.select("a", "b").join(texts.select(F.col("cls").alias("b"), F.col("text").alias("b_text")), "b")
    joined = joined.join(texts.select(F.col("cls").alias("a"), F.col("text").alias("a_text")), "a").select("a", "b", "a_text", "b_text")

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("near-duplicates", _tables.cache_clear)
        last: tuple[bytes | None, np.ndarray] = (None, np.zeros(0, np.uint64))
        for whole in stream:
            for lo in range(0, whole.num_rows, SLICE):
                batch, out = whole.slice(lo, SLICE), []
                left, right = batch.column(0).to_pylist(), batch.column(1).to_pylist()
                for k, (a, b, other) in enumerate(zip(left, right, shingle_sets(C.binary_list(batch.column(3)), width), strict=True)):
                    if a != last[0]:
                        last = (a, next(shingle_sets(C.binary_list(batch.column(2).slice(k, 1)), width)))
                    common = len(np.intersect1d(last[1], other, assume_unique=True))
                    if den * common >= num * (len(last[1]) + len(other) - common):
                        out.append((a, b))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in out], pa.binary()), pa.array([p[1] for p in out], pa.binary())], ["a", "b"])

    return joined.mapInArrow(step, "a binary, b binary")


def _compared(
    docs: DataFrame, starred: DataFrame, narrow: DataFrame, joined: DataFrame, *, id_col: str, text_col: str, width: int, num: int, den: int
) -> DataFrame:
    """Links (a, b) between the components of ``joined`` within each central class's group."""
    member = starred.select(F.col("ca").alias("hub"), F.col("cb").alias("cls")).union(starred.select("ca", "ca").distinct())
    member = member.join(narrow.select("cls", "id", "th", "n"), "cls").join(joined.withColumnRenamed("node", "cls"), "cls", "left")
    member = C.stored(member.withColumn("label", F.coalesce("label", "cls")), "members")
    group = member.groupBy("hub").agg(F.count("*").alias("size"), F.max("n").alias("most"), (F.min("label") != F.max("label")).alias("open"))
    # two classes are compared already; blocks hold about BLOCK classes and BLOCK_VALUES values
    bound = F.greatest(F.lit(8), F.least(F.lit(BLOCK), F.floor(F.lit(BLOCK_VALUES) / F.col("most"))))
    group = C.stored(group.filter("open and size > 2").select("hub", bound.alias("bound")), "groups")
    member = C.stored(member.join(C.small(group), "hub"), "open")
    # components of over a block's size have blocks of their own, the others share some
    parts = member.groupBy("hub", "bound", "label").agg(F.count("*").alias("size"))
    large = C.stored(parts.filter("size > bound").select("hub", "label", F.ceil(F.col("size") / F.col("bound")).cast("int").alias("own")), "large")
    pooled = parts.filter("size <= bound").groupBy("hub").agg(F.greatest(F.lit(1), F.ceil(F.sum("size") / F.first("bound"))).cast("int").alias("pool"))
    member = member.join(C.small(large), ["hub", "label"], "left").join(C.small(C.stored(pooled, "pools")), "hub", "left")
    none = F.lit(None).cast("binary")
    block = F.when(F.col("own").isNotNull(), F.struct(F.col("label").alias("of"), F.pmod(F.xxhash64("cls"), "own").cast("int").alias("part"))).otherwise(F.struct(none.alias("of"), F.pmod(F.xxhash64("cls"), "pool").cast("int").alias("part")))
    member = C.stored(member.select("hub", "cls", "id", "th", "label", block.alias("block")), "blocked")
    blocks = C.stored(member.select("hub", "block").distinct(), "blocks")
    others = blocks.select("hub", F.col("block").alias("other"))
    # blocks of one component aren't compared with each other, nor with themselves
    paired = blocks.join(others, "hub").filter("block.of IS NULL OR other.of IS NULL OR block.of <> other.of").select("hub", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))
    ends = C.small(C.stored(member.select("cls", "id", "th").distinct(), "ends"))
    rows = docs.select(F.col(id_col).alias("d_id"), F.xxhash64(text_col).alias("d_th"), F.col(text_col).alias("text"))
    texts = rows.join(ends, (F.col("d_th") == F.col("th")) & F.col("d_id").eqNullSafe(F.col("id"))).groupBy("cls").agg(F.first("text").alias("text"))

    def build(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("near-duplicates", _tables.cache_clear)
        for batch in (whole.slice(lo, SLICE) for whole in stream for lo in range(0, whole.num_rows, SLICE)):
            sets = [x.view(np.int64) for x in shingle_sets(C.binary_list(batch.column(1)), width)]
            flat = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, sets)]), pa.int32()), pa.array(np.concatenate(sets), pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), flat], ["cls", "set"])

    sets = C.stored(texts.mapInArrow(build, "cls binary, set array<bigint>"), "sets")
    held = member.join(sets, "cls").select("hub", "block", "cls", "label", "set")
    dealt = paired.join(held, ["hub", "block"]).select("hub", "i", "j", "cls", "label", "set", (F.col("block") == F.col("i")).cast("int").alias("own"))

    def step(task: pa.Table) -> pa.Table:
        held = task.column("set").combine_chunks()
        flat, ends = held.flatten().to_numpy().view(np.uint64), np.cumsum(pa.compute.list_value_length(held).to_numpy())
        cls, label = task.column("cls").to_pylist(), np.unique(np.array(task.column("label").to_pylist(), object), return_inverse=True)[1]
        links = joining(np.split(flat, ends[:-1]), label, np.array(task.column("own").to_pylist()), num, den)
        return pa.table({"a": pa.array([cls[x] for x, _ in links], pa.binary()), "b": pa.array([cls[y] for _, y in links], pa.binary())})

    return dealt.groupBy("hub", "i", "j").applyInArrow(step, "a binary, b binary").distinct()


def joining(sets: list[np.ndarray], label: np.ndarray, block: np.ndarray, num: int, den: int) -> list[tuple[int, int]]:
    """A forest of similar pairs that joins the labels. Sets of two blocks are compared across, those of one within."""
    blocks = np.unique(block)
    left, right = np.flatnonzero(block == blocks[0]), np.flatnonzero(block == blocks[-1])
    size = np.array([len(x) for x in sets], np.int64)
    flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), size)
    _, value, held = np.unique(flat, return_inverse=True, return_counts=True)
    shared = held[value] > 1
    number = np.cumsum(held > 1) - 1
    value, owner = number[value[shared]], owner[shared]
    order = np.argsort(value, kind="stable")
    value, owner = value[order], owner[order]
    common = np.zeros((len(left), len(right)), np.float32)
    for lo in range(0, int(number[-1]) + 1 if len(number) else 0, COLUMNS):
        part = slice(*np.searchsorted(value, [lo, lo + COLUMNS]))
        m = np.zeros((len(sets), COLUMNS), np.float32)
        m[owner[part], value[part] - lo] = 1
        common += m[left] @ m[right].T
    common = common.astype(np.int64)
    union = size[left][:, None] + size[right][None, :] - common
    x, y = np.nonzero((den * common >= num * union) & (label[left][:, None] != label[right][None, :]))
    root: dict[int, int] = {}

    def find(k: int) -> int:
        while root.setdefault(k, k) != k:
            root[k] = k = root[root[k]]
        return k

    out = []
    for a, b in zip(left[x].tolist(), right[y].tolist(), strict=True):
        p, q = find(int(label[a])), find(int(label[b]))
        if p != q:
            root[p] = q
            out.append((a, b))
    return out


def near_duplicates(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: tuple[int, int] = (80, 100), k: int = K
) -> DataFrame:
    """id, th, n, component (least id of all documents linked to it) of every row. similarity: as a fraction."""
    return _grouped(docs, id_col, text_col, width, similarity, k).drop("group")


def _grouped(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: tuple[int, int] = (80, 100), k: int = K) -> DataFrame:
    """The same with ``group``: the least class of a row's component, null only for rows without words."""
    num, den = similarity
    o = {"id_col": id_col, "text_col": text_col, "width": width}
    rows = C.stored(sketch(docs, **o, k=k), "sketches")
    one = F.first(F.struct("id", "th", "n", "sketch")).alias("one")
    classes = C.stored(rows.filter("cls is not null").groupBy("cls").agg(F.min("id").alias("least"), one).select("cls", "least", "one.*"), "classes")
    listed = C.stored(_listed(classes, k, num, den), "listed")
    match = _may_match(k, num, den)
    lists = listed.select("cls", "central", F.explode("prefix").alias("v"))
    hubs = C.stored(lists.groupBy("v").agg(F.max(F.struct("central", "cls")).alias("hub"), F.count("*").alias("size")).filter("size > 1"), "hubs")
    starred = C.join_counted(lists, hubs, "v", "size").filter(F.col("cls") != F.col("hub.cls")).select(F.col("hub.cls").alias("ca"), F.col("cls").alias("cb")).distinct()
    starred = C.stored(starred, "starred")
    picked = [F.col(f"{x}.{y}").alias(x + z) for x in "ab" for y, z in (("cls", ""), ("id", "_id"), ("th", "_th"))]
    narrow = listed.select("cls", "id", "th", "n", "sketch")
    pairs = starred.join(narrow.alias("a"), F.col("ca") == F.col("a.cls")).join(narrow.alias("b"), F.col("cb") == F.col("b.cls")).filter(match).select(*picked)
    pairs = C.stored(pairs, "pairs")
    links = C.stored(_verified(docs, pairs, **o, num=num, den=den), "similar")
    joined = C.stored(components(links), "components")

    more = C.stored(_compared(docs, starred, narrow, joined, **o, num=num, den=den), "joining")
    if more.limit(1).count():
        joined = C.stored(components(links.union(more)), "components")

    members = joined.join(classes.select(F.col("cls").alias("node"), "least"), "node")
    leasts = members.groupBy("label").agg(F.min("least").alias("component"))
    of_class = classes.select("cls", "least").join(members.select(F.col("node").alias("cls"), "label"), "cls", "left").join(leasts, "label", "left")
    of_class = C.stored(of_class.select("cls", F.coalesce("component", "least").alias("component"), F.coalesce("label", "cls").alias("group")), "members")
    return rows.select("id", "th", "n", "cls").join(of_class, "cls", "left").select(
        F.col("id").alias(id_col), "th", "n", F.when(F.col("cls").isNull(), F.col("id")).otherwise(F.col("component")).alias("component"), "group"
    )


def deduplicated(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", wordless: bool = False, **options) -> DataFrame:
    """``docs`` (all columns) with one row of each component: the least id, and of its rows the first by text hash.

    Of rows with this id and text any one stays. A component without ids is represented by its least text hash. Rows without words are in no component; with
    ``wordless`` they stay, each on its own, else they go.
    """
    found = _grouped(docs, id_col=id_col, text_col=text_col, **options).withColumnRenamed(id_col, "id")
    one = F.struct(F.coalesce(F.col("id") != F.col("component"), F.lit(True)).alias("other"), F.col("id").alias("k_id"), F.col("th").alias("k_th"), "times")
    keep = found.filter(F.col("n") > 0).groupBy("group", "id", "component", "th").agg(F.count("*").alias("times")).groupBy("group").agg(F.min(one).alias("x"))
    keep = C.stored(keep.groupBy("x.k_id", "x.k_th").agg(F.max("x.times").alias("times")), "kept")
    # the row as one column, so that no name of its columns can clash; blanks between words are those of word_hashes
    rows = docs.select(F.struct("*").alias("row"), F.col(id_col).alias("id"), F.xxhash64(text_col).alias("th"), F.coalesce(text_col, F.lit("")).rlike(r"[^\x20\x09-\x0D]").alias("words"))
    is_kept = (F.col("th") == F.col("k_th")) & F.col("id").eqNullSafe(F.col("k_id"))
    kept = rows.join(keep.filter("times = 1").select("k_id", "k_th"), is_kept, "left_semi")
    # only what stands in several rows is moved to find one of them
    several = C.small(C.stored(keep.filter("times > 1").select("k_id", "k_th"), "several"))
    again = rows.join(several, is_kept, "left_semi").groupBy("id", "th").agg(F.first("row").alias("row"))
    kept = kept.select("row").union(again.select("row"))
    return (kept.union(rows.filter("not words").select("row")) if wordless else kept).select("row.*")


def op7_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: three-word shingles, similarity 0.85."""
    found = near_duplicates(C.table(spark, sf_dir, "documents"), width=3, similarity=(85, 100))
    return found.select("doc_id", F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), (F.col("doc_id") == F.col("component")).alias("kept"))
