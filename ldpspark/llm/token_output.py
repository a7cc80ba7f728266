"""Token-id output: frequency-ranked ids in byte-aligned variable-length coding with separate control bytes.

Texts are brought into ascending id order by range partitioning, tokenised, and packed into blocks. A block is one
self-contained byte string of the file format below; blocks are written as rows of Parquet files, whose commit protocol
survives lost executors on any store, and ``export`` copies blocks to plain files where a path can be written.

Block format, all numbers little-endian: magic ``TIB1``, four uint64 (documents, tokens, ranks, data bytes), the rank
table (uint32 ids, commonest first, ties to the smaller id), token counts of the documents (uint32), control bytes (two
bits a token, four tokens a byte, lowest bits first: length of its rank in bytes less one), data bytes (ranks). The rank
of an id is its place in the block's own table, so a block needs one pass over the texts and decodes alone.
Decoding looks each control byte up in a table of its four lengths, sums lengths to offsets and gathers bytes.

Ids are those of the tokenizers library. Where a tokenizer splits texts as :class:`Pieces` does, each distinct piece is
merged once for as long as it is kept; other texts (beyond Latin-1, or naming special tokens) and tokenizers go whole.

Defined results: null texts are empty; every document gets the end id; null ids come first; equal ids stand in order of
their texts; an empty table gives no blocks and no rows.
"""

from __future__ import annotations

import json
import os
import re
import struct
import unicodedata
import zlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

MAGIC, HEAD = b"TIB1", struct.Struct("<4sQQQQ")
BLOCK_TOKENS, CHUNK_BYTES = 1 << 18, 1 << 20
KEPT_PIECES = 250_000
#: Lengths in bytes of the four tokens of each control byte.
LENGTHS = np.array([[(c >> s & 3) + 1 for s in (0, 2, 4, 6)] for c in range(256)], np.int64)


def encode_block(counts: np.ndarray, ids: np.ndarray) -> bytes:
    """``counts`` tokens a document, their ids one after the other."""
    seen = np.bincount(ids) if len(ids) else np.zeros(0, np.int64)
    order = np.lexsort((np.arange(len(seen)), -seen))
    ranked = order[: int((seen > 0).sum())]
    rank_of = np.zeros(len(seen), np.uint32)
    rank_of[ranked] = np.arange(len(ranked), dtype=np.uint32)
    ranks = rank_of[ids] if len(ids) else np.zeros(0, np.uint32)
    size = 1 + (ranks > 0xFF) + (ranks > 0xFFFF) + (ranks > 0xFFFFFF)
    code = np.zeros(-(-len(ranks) // 4) * 4, np.uint8)
    code[: len(ranks)] = size - 1
    quads = code.reshape(-1, 4)
    control = quads[:, 0] | quads[:, 1] << 2 | quads[:, 2] << 4 | quads[:, 3] << 6
    end = np.cumsum(size)
    data = np.zeros(int(end[-1]) if len(end) else 0, np.uint8)
    at = end - size
    for k in range(4):
        m = slice(None) if k == 0 else np.flatnonzero(size > k)
        data[at[m] + k] = (ranks[m] >> np.uint32(8 * k)) & np.uint32(0xFF)
    head = HEAD.pack(MAGIC, len(counts), len(ids), len(ranked), len(data))
    return b"".join([head, ranked.astype("<u4").tobytes(), np.asarray(counts, "<u4").tobytes(), control.astype(np.uint8).tobytes(), data.tobytes()])


def decode_block(block: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Token counts of the documents and all ids (uint32) of a block."""
    magic, docs, tokens, ranked, size = HEAD.unpack_from(block)
    if magic != MAGIC:
        raise ValueError("not a token block")
    at = HEAD.size
    table = np.frombuffer(block, "<u4", ranked, at)
    counts = np.frombuffer(block, "<u4", docs, at := at + 4 * ranked)
    control = np.frombuffer(block, np.uint8, -(-tokens // 4), at := at + 4 * docs)
    data = np.concatenate([np.frombuffer(block, np.uint8, size, at + len(control)), np.zeros(4, np.uint8)])
    length = LENGTHS[control].reshape(-1)[:tokens]
    start = np.cumsum(length) - length
    ranks = data[start].astype(np.uint32)
    for k in range(1, 4):
        m = np.flatnonzero(length > k)
        if not len(m):
            break
        ranks[m] |= data[start[m] + k].astype(np.uint32) << np.uint32(8 * k)
    return counts, table[ranks] if tokens else np.zeros(0, np.uint32)


#: The normalisation and splitting that :class:`Pieces` repeats for Latin-1 texts; fixed values of the tokenizer's format.
KNOWN_NORMALIZER = ["NFC", "Replace", "Lowercase"]
KNOWN_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


class Pieces:
    """Splits a Latin-1 text into the tokenizer's own pieces: lower case, letters, single digits, other marks."""

    def __init__(self) -> None:
        kind = [unicodedata.category(chr(i))[0] for i in range(256)]
        space = b" \t\n\r\x0b\x0c\x85\xa0"
        letters, numbers = (b"".join(re.escape(bytes([i])) for i in range(256) if kind[i] == k) for k in "LN")
        self.find = re.compile(b"[" + letters + b"]+|[" + numbers + b"]|'s|'t|'re|'ve|'m|'ll|'d|[^" + re.escape(space) + letters + numbers + b"]+").findall
        self.lower = bytes(32 if i in space else ord(c) if len(c := chr(i).lower()) == 1 and ord(c) < 256 else i for i in range(256))
        self.plain = bytes(i for i in range(256) if kind[i] == "L") + b" "
        self.hard = frozenset(i for i in range(256) if kind[i] == "N") | {39}
        self.run = re.compile(b"[^ " + letters + b"]{2}").search

    def __call__(self, text: str) -> list[bytes] | None:
        """None: the text has other characters, or may name a special token."""
        try:
            raw = text.encode("latin-1")
        except UnicodeEncodeError:
            return None
        if b"<|" in raw:
            return None
        raw = raw.translate(self.lower)
        marks = set(raw.translate(None, self.plain))
        if len(marks) > 8 or not marks.isdisjoint(self.hard) or self.run(raw):
            return self.find(raw)
        # marks that stand alone among letters are pieces of their own: blanks around them make all pieces words
        for m in marks:
            raw = raw.replace(bytes([m]), bytes([32, m, 32]))
        return raw.split()


def byte_letters() -> dict[int, str]:
    """The printable letter of each byte that byte-level vocabularies use."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [i for i in range(256) if i not in own]
    return {i: chr(i) for i in own} | {i: chr(256 + k) for k, i in enumerate(rest)}


class _Numbers(dict):
    """Numbers pieces as they come; ``new`` lists those that were not known."""

    def __init__(self) -> None:
        super().__init__()
        self.new: list[bytes] = []

    def __missing__(self, piece: bytes) -> int:
        out = self[piece] = len(self)
        self.new.append(piece)
        return out


class Encoder:
    """Ids of texts as the tokenizer gives them; where its way of splitting is known, each distinct piece is merged once.

    A second tokenizer without normalisation merges new pieces, many joined by blanks at a time: the mark of a word's
    end, which every piece's last id carries, tells where each piece's ids stop.
    """

    def __init__(self, path: str, end_id: int | None):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        self.path, self.end, self.most = path, end_id, max([*made["model"]["vocab"].values(), *(x["id"] for x in made.get("added_tokens") or [])])
        self._whole = None
        kinds = [x.get("type") for x in (made.get("normalizer") or {}).get("normalizers", [])]
        splits = [x.get("pattern", {}).get("Regex") for x in (made.get("pre_tokenizer") or {}).get("pretokenizers", [])]
        model, suffix = made["model"], made["model"].get("end_of_word_suffix")
        self.pieces = Pieces() if kinds == KNOWN_NORMALIZER and splits[:1] == [KNOWN_PATTERN] and suffix and not model.get("dropout") else None
        if self.pieces:
            self.merger = Tokenizer.from_str(json.dumps(made | {"normalizer": None, "pre_tokenizer": {"type": "WhitespaceSplit"}, "post_processor": None, "added_tokens": []}))
            self.ends = np.zeros(max(model["vocab"].values()) + 1, bool)
            self.ends[[i for t, i in model["vocab"].items() if t.endswith(suffix)]] = True
            self.letters = byte_letters()
            del self.letters[32]
        self._clear()

    def _clear(self) -> None:
        self.number, self.uses = _Numbers(), np.zeros(1 << 16, np.int32)
        self.size, self.first, self.flat = np.zeros(1 << 16, np.int32), np.zeros(1 << 16, np.int64), np.zeros(1 << 18, np.uint16 if self._narrow() else np.uint32)
        self.used = self.known = 0

    def _forget(self) -> None:
        """Keeps the pieces used most, a quarter of what may be kept; their use counts for less from then on."""
        kept = np.argsort(-self.uses[: self.known], kind="stable")[: KEPT_PIECES // 4]
        uses, names = self.uses[kept] // 2, list(self.number)
        size, first, flat = self.size[kept].astype(np.int64), self.first[kept], self.flat
        ids = flat[np.repeat(first - (np.cumsum(size) - size), size) + np.arange(size.sum())]
        self._clear()
        for k in kept.tolist():
            dict.__setitem__(self.number, names[k], len(self.number))
        self.known, self.used = len(kept), len(ids)
        fit = lambda x, n: np.concatenate([x, np.zeros(max(0, n - len(x)), x.dtype)])
        self.uses, self.size, self.first = fit(uses, 1 << 16), fit(size.astype(np.int32), 1 << 16), fit(np.cumsum(size) - size, 1 << 16)
        self.flat = fit(ids, 1 << 18)

    def _narrow(self) -> bool:
        return self.most < 1 << 16

    @property
    def tokenizer(self):
        """For texts that go whole; loaded when there is one."""
        if self._whole is None:
            from tokenizers import Tokenizer

            self._whole = Tokenizer.from_file(self.path)
        return self._whole

    def _learn(self, new: list[bytes]) -> None:
        for lo in range(0, len(new), 4000):
            part = new[lo : lo + 4000]
            text = b" ".join(part).decode("latin-1").encode().decode("latin-1").translate(self.letters)
            ids = np.array(self.merger.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32)
            stop = np.flatnonzero(self.ends[ids]) + 1
            if len(stop) != len(part):
                raise ValueError("pieces without a word end")
            n = self.known
            while n + len(part) > len(self.size):
                self.size, self.first, self.uses = (np.concatenate([x, np.zeros_like(x)]) for x in (self.size, self.first, self.uses))
            while self.used + len(ids) > len(self.flat):
                self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
            self.flat[self.used : self.used + len(ids)] = ids
            self.size[n : n + len(part)] = np.diff(stop, prepend=0)
            self.first[n : n + len(part)] = self.used + np.concatenate(([0], stop[:-1]))
            self.used += len(ids)
            self.known += len(part)

    def __call__(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Token counts with the end id, and all ids, of a chunk of texts."""
        split = [self.pieces(t) if self.pieces else None for t in texts]
        whole = [k for k, x in enumerate(split) if x is None]
        ready = {k: np.array(e.ids, np.uint32) for k, e in zip(whole, self.tokenizer.encode_batch_fast([texts[k] for k in whole], add_special_tokens=False), strict=True)} if whole else {}
        if len(self.number) > KEPT_PIECES:
            self._forget()
        counts = [len(x) if x else 0 for x in split]
        n = np.fromiter(map(self.number.__getitem__, chain.from_iterable(x for x in split if x)), np.int64, sum(counts))
        self._learn(self.number.new)
        self.number.new = []
        self.uses[: self.known] += np.bincount(n, minlength=self.known).astype(np.int32)
        size = self.size[n].astype(np.int64)
        total = np.concatenate(([0], np.cumsum(size)))
        # gather all pieces' ids: place in the flat store = first of the piece + place within it
        ids = self.flat[np.repeat(self.first[n] - total[:-1], size) + np.arange(total[-1])].astype(np.uint32)
        stop = total[np.cumsum(counts)]
        if not ready and self.end is None:
            return np.diff(stop, prepend=0), ids
        if not ready:
            return np.diff(stop, prepend=0) + 1, np.insert(ids, stop, np.uint32(self.end))
        out, at = [], 0
        for k, e in enumerate(stop.tolist()):
            own = ready.get(k, ids[at:e])
            at = e
            out.append(own if self.end is None else np.append(own, np.uint32(self.end)))
        return np.array([len(x) for x in out], np.int64), np.concatenate(out) if out else ids


@lru_cache(maxsize=2)
def encoder(path: str, end_id: int | None) -> Encoder:
    """One for all tasks of a worker."""
    return Encoder(path, end_id)


def encode(
    docs: DataFrame, tokenizer: str, *, end_id: int | None = 2, id_col: str = "doc_id", text_col: str = "text", block_tokens: int = BLOCK_TOKENS,
) -> DataFrame:
    """Blocks in ascending id order: part, part_start, block, ids (of the documents), payload. Store it, then ``decode``.

    part: the range partition; part_start: number of the part's tokens before the block. Blocks of a part come in order
    from one task, which holds about one block; a text longer than a block makes a block of its own.
    """
    id_type = docs.schema[id_col].dataType.simpleString()
    ordered = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).repartitionByRange("id").sortWithinPartitions("id", "text")

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        C.own("token output", encoder.cache_clear)
        part, encoding = TaskContext.get().partitionId(), encoder(tokenizer, end_id)
        held: list[tuple[list, np.ndarray, np.ndarray]] = []
        size = before = number = 0

        def out() -> pa.RecordBatch:
            nonlocal held, size, before, number
            ids, counts = [i for x, _, _ in held for i in x], np.concatenate([c for _, c, _ in held])
            payload = encode_block(counts, np.concatenate([t for _, _, t in held]))
            row = pa.RecordBatch.from_pydict({"part": [part], "part_start": [before], "block": [number], "tokens": [size], "ids": [ids], "payload": [payload]}, schema)
            held, before, size, number = [], before + size, 0, number + 1
            return row

        schema = None
        for batch in stream:
            schema = schema or pa.schema([("part", pa.int32()), ("part_start", pa.int64()), ("block", pa.int32()), ("tokens", pa.int64()), ("ids", pa.list_(batch.schema.field(0).type)), ("payload", pa.binary())])
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            for lo, hi in chunks(pc.binary_length(texts).to_numpy(zero_copy_only=False), min(CHUNK_BYTES, 4 * block_tokens)):
                counts, tokens = encoding(texts.slice(lo, hi - lo).to_pylist())
                held.append((ids[lo:hi], counts, tokens))
                size += len(tokens)
                if size >= block_tokens:
                    yield out()
        if held:
            yield out()

    return ordered.mapInArrow(step, f"part int, part_start bigint, block int, tokens bigint, ids array<{id_type}>, payload binary")


def chunks(sizes: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Bounds of consecutive texts of about ``most`` bytes together."""
    lo, total = 0, 0
    for k, n in enumerate(sizes.tolist()):
        total += n
        if total >= most:
            yield lo, k + 1
            lo, total = k + 1, 0
    if lo < len(sizes):
        yield lo, len(sizes)


def decode(blocks: DataFrame, id_col: str = "doc_id", tokens: bool = True) -> DataFrame:
    """id, start (tokens of all documents before it), n_tokens, ids_crc32 and, if asked for, the token ids."""
    id_type = blocks.schema["ids"].dataType.elementType.simpleString()
    ends = blocks.groupBy(F.col("part").alias("p")).agg(F.sum("tokens").alias("in_part"))
    from pyspark.sql import Window

    # one row a range partition: their number is set by the shuffle, not by the documents
    base = ends.withColumn("base", F.sum("in_part").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, 0)) - F.col("in_part"))
    placed = blocks.join(F.broadcast(base), F.col("part") == F.col("p")).select((F.col("base") + F.col("part_start")).alias("start"), "ids", "payload")

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        C.own("token input", lambda: None)
        for batch in stream:
            for k in range(batch.num_rows):
                counts, found = decode_block(batch.column(2)[k].as_py())
                end = np.cumsum(counts.astype(np.int64))
                raw, at = memoryview(found.astype("<u4").tobytes()), (end - counts)
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at.tolist(), end.tolist(), strict=True)]
                out = [batch.column(1)[k].values, pa.array(batch.column(0)[k].as_py() + at), pa.array(counts.astype(np.int64)), pa.array(crc, pa.int64())]
                if tokens:
                    out.append(pa.ListArray.from_arrays(pa.array(np.concatenate(([0], end)).astype(np.int32)), pa.array(found.astype(np.int64))))
                yield pa.RecordBatch.from_arrays(out, [id_col, "start", "n_tokens", "ids_crc32", "tokens"][: len(out)])

    return placed.mapInArrow(step, f"`{id_col}` {id_type}, start bigint, n_tokens bigint, ids_crc32 bigint" + ", tokens array<bigint>" * tokens)


def export(blocks: DataFrame, folder: str) -> int:
    """Blocks as plain files ``part-block.tib`` below a folder that all executors share; the tasks write them.

    A file gets its name when it is whole and its content is the block's alone, so a task that runs again does no harm.
    """

    def step(stream: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os
        import uuid

        os.makedirs(folder, exist_ok=True)
        for batch in stream:
            for part, block, payload in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                path = f"{folder}/{part:06d}-{block:06d}.tib"
                with open(f"{path}.{uuid.uuid4().hex}", "wb") as f:
                    f.write(payload.as_py())
                os.replace(f.name, path)
            yield pa.RecordBatch.from_pydict({"n": pa.array([batch.num_rows], pa.int64())})

    return blocks.select("part", "block", "payload").mapInArrow(step, "n bigint").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def token_output(docs: DataFrame, tokenizer: str | None = None, **options) -> DataFrame:
    """Encodes ``docs`` into stored blocks and reads them back: id, start, n_tokens, ids_crc32."""
    if tokenizer is None:
        import public_tokenizers

        tokenizer = public_tokenizers.path("word_bpe_49k.json")
    return decode(C.stored(encode(docs, tokenizer, **options), "tokens"), options.get("id_col", "doc_id"), tokens=False)


def op4_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract digest of the written blocks over ``documents``."""
    return token_output(C.table(spark, sf_dir, "documents"))
