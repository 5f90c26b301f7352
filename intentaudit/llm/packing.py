"""Packing token pieces into fixed-length sequences, shortest pack first.

One pass tokenizes the documents, cuts them into pieces and numbers the pieces
of each length within their task. The histogram of lengths (at most
``max_len`` bins) is packed on the driver by pattern counts, longest length
first, each into the packs with the lowest fill; the patterns then meet the
pieces again by (length, rank).
"""

from __future__ import annotations

import heapq
import os
import re
import struct
import unicodedata
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_batches, materialize, text_of

#: Fixed value: the byte-level vocabulary's pre-token pattern.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


#: The same split by the standard ``re``, whose \w also holds letter-like and other numbers and whose \s the separators 1C-1F: for texts without those.
_PLAIN = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")
_CONTROL = "\x1c\x1d\x1e\x1f"
_ODD = frozenset(_CONTROL) | {c for c in map(chr, range(0x110000)) if unicodedata.category(c) in ("Nl", "No")}
_ODD_LATIN = [c for c in sorted(_ODD) if c <= "\xff"]


def plain_split(text: str) -> bool:
    """Whether the standard ``re`` splits this text alike."""
    if text.isascii():
        return not any(c in text for c in _CONTROL)
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return _ODD.isdisjoint(text)
    return not any(c in text for c in _ODD_LATIN)


def byte_alphabet() -> dict[int, str]:
    """Byte to printable character, the byte-level vocabulary's rule: printable bytes stand for themselves, the rest follow from 256 on."""
    keep = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    rest = [b for b in range(256) if b not in keep]
    return {b: chr(b) for b in keep} | {b: chr(256 + i) for i, b in enumerate(rest)}


class PieceEncoder(dict):
    """Token ids by ``tokenizers``, remembered per pre-token.

    A byte-level BPE encodes each pre-token by itself, so ids of a text are
    the ids of its pre-tokens in order; unseen ones go to the library's model.
    Memory is bounded: past ``limit`` entries the store is emptied. Texts
    holding an added token's string go to the library whole.
    """

    def __init__(self, path: str, limit: int = 600_000):
        super().__init__()
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import regex
        from tokenizers import Tokenizer

        self.tok, self.limit, self.alphabet = Tokenizer.from_file(path), limit, byte_alphabet()
        self.model = self.tok.model
        self.find = regex.compile(SPLIT).findall
        self.added = [t.content for t in self.tok.get_added_tokens_decoder().values()]

    def __missing__(self, part: str) -> bytes:
        if len(self) >= self.limit:
            self.clear()
        spelled = part.encode().decode("latin-1").translate(self.alphabet)
        ids = self[part] = struct.pack(f"<{len(t)}I", *(x.id for x in t)) if (t := self.model.tokenize(spelled)) else b""
        return ids

    def __call__(self, text: str) -> bytes:
        """Little-endian unsigned 32-bit ids."""
        if any(a in text for a in self.added):
            return np.asarray(self.tok.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        find = _PLAIN.findall if plain_split(text) else self.find
        return b"".join(map(self.__getitem__, find(text)))


def pack_histogram(counts: dict[int, int], max_len: int) -> list[tuple[int, list[int]]]:
    """Patterns [(packs, lengths)] for a histogram of piece lengths.

    Lengths are placed longest first, each into the packs with the lowest
    fill, all packs of a pattern at once; new packs open when none fits.
    """
    heap: list[tuple[int, int, list[int]]] = []  # fill, order of making, lengths
    packs: dict[int, int] = {}
    made = 0

    def add(fill: int, lengths: list[int], n: int) -> None:
        nonlocal made
        packs[made] = n
        heapq.heappush(heap, (fill, made, lengths))
        made += 1

    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            if heap and heap[0][0] + length <= max_len:
                fill, key, lengths = heapq.heappop(heap)
                n = packs.pop(key)
                take = min(n, left)
                if n > take:
                    add(fill, lengths, n - take)
                left -= take
                add(fill + length, [*lengths, length], take)
            else:
                add(length, [length], left)
                left = 0
    return [(packs[key], lengths) for _, key, lengths in sorted(heap, key=lambda x: x[1])]


def slots(patterns: list[tuple[int, list[int]]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, end rank, first sequence, offset) of every place."""
    used: Counter = Counter()
    out, base = [], 0
    for packs, lengths in patterns:
        at = 0
        for length in lengths:
            out.append((length, used[length], used[length] + packs, base, at))
            used[length] += packs
            at += length
        base += packs
    return out


def tokenized_pieces(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", max_len: int = 2048, end_id: int = 1) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, part, nth): pieces, numbered per length within their task."""

    def cut(batches):
        encode, part, seen = PieceEncoder(tokenizer), TaskContext.get().partitionId(), Counter()
        tail = np.asarray([end_id], "<u4").tobytes()
        for b in batches:
            rows = []
            for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()):
                ids = encode(text or "") + tail
                n = len(ids) // 4
                for start in range(0, n, max_len):
                    piece = ids[4 * start : 4 * (start + max_len)]
                    length = len(piece) // 4
                    rows.append((doc, start, length, zlib.crc32(piece), n, part, seen[length]))
                    seen[length] += 1
            if rows:
                c = list(zip(*rows))
                yield pa.record_batch([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.int64()), pa.array(c[3], pa.int64()), pa.array(c[4], pa.int64()), pa.array(c[5], pa.int32()), pa.array(c[6], pa.int64())], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "part", "nth"])

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"))
    return map_batches(texts, cut, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, part int, nth long")


def pack(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", max_len: int = 2048, end_id: int = 1) -> DataFrame:
    """One row per piece: where it lies in its document and in its sequence.

    A null text is empty and gives the end id alone. Repeated rows are packed
    as often as they occur. An empty table gives an empty result. Extra columns are ignored.
    """
    pieces = materialize(tokenized_pieces(docs, tokenizer, id_col, text_col, max_len, end_id))
    spark = docs.sparkSession
    counts = pieces.groupBy("length", "part").agg(F.count("*").alias("n"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most max_len rows
    places = slots(pack_histogram(histogram, max_len))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    first = counts.select("length", "part", F.coalesce(F.sum("n").over(before), F.lit(0).cast("long")).alias("before"))
    ranked = pieces.join(first, ["length", "part"]).withColumn("rank", F.col("before") + F.col("nth"))
    # patterns split at most twice per length, so places stay within a few times max_len rows
    where = spark.createDataFrame(places or [(0, 0, 0, 0, 0)], "length long, lo long, hi long, base long, offset long")
    return ranked.join(F.broadcast(where), "length").filter((F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi"))).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.col("base") + F.col("rank") - F.col("lo")).alias("sequence_id"), "offset")
