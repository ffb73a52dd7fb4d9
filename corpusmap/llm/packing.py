"""Best-fit-decreasing packing of token sequences into windows.

Documents over a window are first cut into full windows. The rest is packed in
groups of near-equal token counts, each in decreasing order into the tightest
open window, found by a segment tree over remaining capacities.
"""

from __future__ import annotations

import json
import sys
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmap.llm.common import documents, lean, materialize, ship, text_or_empty

WINDOW = 2048
END_ID = 1
CACHE = 500_000
SLICE = 512  # documents whose ids are held at once


class CapacityTree:
    """Open windows by remaining capacity; finds the smallest capacity that suffices in log time."""

    def __init__(self, most: int):
        self.leaves = 1 << most.bit_length()
        self.count = [0] * (2 * self.leaves)
        self.open: dict[int, list[int]] = {}

    def add(self, capacity: int, window: int) -> None:
        self.open.setdefault(capacity, []).append(window)
        at = capacity + self.leaves
        while at:
            self.count[at] += 1
            at >>= 1

    def take(self, need: int) -> tuple[int, int] | None:
        """Removes and returns ``(capacity, window)`` with the least capacity at or above ``need``."""
        at = need + self.leaves
        if not self.count[at]:
            while at > 1 and (at & 1 or not self.count[at + 1]):  # up to the first right neighbour that holds any
                at >>= 1
            if at <= 1:
                return None
            at += 1
            while at < self.leaves:
                at = 2 * at if self.count[2 * at] else 2 * at + 1
        capacity = at - self.leaves
        window = self.open[capacity].pop()
        while at:
            self.count[at] -= 1
            at >>= 1
        return capacity, window


def best_fit_decreasing(lengths: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """Window number and offset of each piece; every length is 1 to ``window``."""
    where, offset = np.zeros(len(lengths), dtype=np.int64), np.zeros(len(lengths), dtype=np.int64)
    tree, n = CapacityTree(window), 0
    for i in np.argsort(-lengths, kind="stable").tolist():
        need = int(lengths[i])
        found = tree.take(need)
        if found is None:
            capacity, w = window, n
            n += 1
        else:
            capacity, w = found
        where[i], offset[i] = w, window - capacity
        if capacity > need:
            tree.add(capacity - need, w)
    return where, offset


def _byte_of() -> dict[str, int]:
    """The byte behind each printable stand-in of a byte-level vocabulary."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}


class WordCore:
    """Merges of single words by a rank table; a byte that UTF-8 never uses stands for the end of a word.

    The first merge of a word joins its last byte with that mark, which gives
    the symbols the vocabulary starts from; then merges follow in their order.
    """

    MARK = b"\xff"

    def __init__(self, path: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        of, suffix = _byte_of(), model["end_of_word_suffix"]

        def raw(token: str) -> bytes:
            end = token.endswith(suffix)
            return bytes(of[c] for c in (token[: -len(suffix)] if end else token)) + self.MARK * end

        order = [bytes([b]) for b in range(256)] + [bytes([b]) + self.MARK for b in range(255)]
        order += [raw(a) + raw(b) for a, b in (m.split(" ") if isinstance(m, str) else m for m in model["merges"])]
        ranks = {t: i for i, t in enumerate(dict.fromkeys(order))}
        ids = {raw(t): i for t, i in model["vocab"].items() if all(c in of for c in t)}
        self.bytes_of = [ids[t].to_bytes(4, "little") if t in ids else b"" for t in ranks]
        self.piece = tiktoken.Encoding("words", pat_str=r"\S+", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece

    def __call__(self, word: str) -> bytes:
        of = self.bytes_of
        return b"".join([of[i] for i in self.piece(word.encode() + self.MARK)])


class CachedEncoder:
    """Token ids, little-endian in 32 bits, of whole texts; chunks between blanks are encoded once and kept.

    No token of the vocabulary and no rule of its normaliser reaches over a
    blank or line feed, so the ids of a text are those of its chunks in turn.
    Letters, or letters and then marks, are one or two words and go to
    :class:`WordCore`; whatever else goes to the tokenizer itself. The cache
    is emptied when full.
    """

    #: fixed values: marks that form a word of their own after letters
    MARKS = "!\"#$%&()*+,-./:;=>?@[\\]^_`{|}~"

    def __init__(self, path: str, most: int = CACHE):
        from tokenizers import Tokenizer

        self.inner, self.core, self.most, self.seen = Tokenizer.from_file(path), WordCore(path), most, {"": b""}

    def _learn(self, chunk: str) -> bytes:
        head = chunk.rstrip(self.MARKS)
        word = head.lower() if head.isascii() else unicodedata.normalize("NFC", head).lower() if "\u03a3" not in head else "?"
        if word.isalpha():
            ids = self.core(word)
        elif not head:
            ids = b""
        else:
            return np.array(self.inner.encode(chunk, add_special_tokens=False).ids, dtype="<u4").tobytes()
        return ids + (self.core(chunk[len(head):]) if len(head) < len(chunk) else b"")

    @staticmethod
    def _folded(text: str) -> str:
        """The text in lower case where the tokenizer would fold it to just that, else as it is."""
        low = text.lower()
        if "<|" in text:  # names of special tokens are told apart by case
            return text
        if text.isascii():
            return low
        plain = "\u0130" not in text and "\u03a3" not in text
        return low if plain and unicodedata.is_normalized("NFC", text) and unicodedata.is_normalized("NFC", low) else text

    def __call__(self, text: str) -> bytes:
        chunks = self._folded(text).replace("\n", " ").split(" ")
        try:
            return b"".join(map(self.seen.__getitem__, chunks))
        except KeyError:
            parts, seen = [], self.seen
            if len(seen) >= self.most:
                seen = self.seen = {"": b""}
            for c in chunks:
                ids = seen.get(c)
                if ids is None:
                    ids = self._learn(c)
                    if len(c) < 64 and len(seen) < self.most:
                        seen[c] = ids
                parts.append(ids)
            return b"".join(parts)


def _encoder(path: str) -> CachedEncoder:
    """One per worker process: workers outlive tasks. Tasks of other operators drop it."""
    held = sys.__dict__.setdefault("_corpusmap_encoders", {})
    if path not in held:
        held[path] = CachedEncoder(path)
    return held[path]


def pieces(docs: DataFrame, path: str, window: int = WINDOW, with_ids: bool = False) -> DataFrame:
    """``(doc_id, start, length, ids_crc32, doc_tokens[, ids])``: every document as full windows and a rest.

    A document is the ids of its text (null: empty), then the end id; an empty
    text gives one piece of length 1. Repeated rows give repeated pieces.
    """
    ship(docs.sparkSession)
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"] + ["ids"] * with_ids
    end = END_ID.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _encoder(path)
        for b in (whole.slice(at, SLICE) for whole in batches for at in range(0, whole.num_rows, SLICE)):
            rows: list[tuple] = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = encode(text.as_py()) + end
                n = len(ids) // 4
                for start in range(0, n, window):
                    part = ids[4 * start: 4 * (start + window)]
                    rows.append((doc, start, len(part) // 4, zlib.crc32(part), n) + ((np.frombuffer(part, dtype="<u4").astype(np.int32),) if with_ids else ()))
            cols = list(zip(*rows, strict=True)) or [()] * len(names)
            types = [b.schema.field(0).type, *[pa.int64()] * 4, pa.list_(pa.int32())]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), type=t) for c, t in zip(cols, types)], names=names)

    kept = docs.select("doc_id", text_or_empty("text").alias("text"))
    like = kept.select("doc_id").withColumns({n: F.lit(0).cast("long") for n in names[1:5]})
    schema = (like.withColumn("ids", F.array(F.lit(0))) if with_ids else like).schema
    return kept.mapInArrow(lean(run, "_corpusmap_encoders"), schema)


def pack(found: DataFrame, window: int = WINDOW, group_tokens: int = 4_000_000) -> DataFrame:
    """``pieces`` plus ``sequence_id long, offset long``; offsets have no gaps, no sequence exceeds the window.

    Full windows are sequences of their own. The others are dealt by hash into
    groups of about ``group_tokens`` tokens that are packed apart, so a task's
    memory is bounded and the half-open windows of a group do not count.
    """
    rest = found.filter(F.col("length") < window)
    tokens = rest.agg(F.sum("length")).first()[0] or 0
    groups = max(1, -(-tokens // group_tokens))
    full = found.filter(F.col("length") >= window).withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    names = found.columns

    def run(key: tuple, table: pa.Table) -> pa.Table:
        order = table.sort_by([("length", "descending"), ("doc_id", "ascending"), ("start", "ascending")])
        where, offset = best_fit_decreasing(order.column("length").to_numpy(), window)
        order = order.select(names)
        return order.append_column("sequence_id", pa.array(key[0].as_py() + groups * where)).append_column("offset", pa.array(offset))

    # the pieces are a written table; its row numbers deal equal rows, however many, to all groups
    dealt = rest.withColumn("deal", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32", F.monotonically_increasing_id()), F.lit(groups)).cast("long"))
    packed = dealt.groupBy("deal").applyInArrow(run, full.schema)
    return full.unionByName(packed)


def padding(packed: DataFrame, window: int = WINDOW) -> DataFrame:
    """One row: sequences, tokens, padding to the window; a sequence of a power of two in length needs none."""
    seqs = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    return seqs.agg(F.count(F.lit(1)).alias("sequences"), F.sum("n").alias("tokens"), F.sum(F.when(F.col("n").bitwiseAND(F.col("n") - 1) == 0, 0).otherwise(window - F.col("n"))).alias("padding"))


def pack_documents(docs: DataFrame, path: str | None = None, window: int = WINDOW, with_ids: bool = False) -> DataFrame:
    """Documents to packed pieces; see :func:`pieces` and :func:`pack`. An empty table gives an empty result."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    return pack(materialize(pieces(docs, path, window, with_ids), "pieces"), window)


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(documents(spark, sf_dir)).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
