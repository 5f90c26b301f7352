"""Language-model scoring with a probabilistic suffix tree over words.

Contexts are runs of up to ``depth`` words seen at least ``support`` times, a
count that does not depend on the size of the corpus. A context stays in the tree if
the words that follow it are better foretold by its own counts, each
occurrence left out in turn, than by those of its suffix, by more than noise
explains. A retained context keeps all its next words; its distribution is smoothed towards its
suffix's, down to the unigram root; a word is scored in the state of the
longest retained suffix of what precedes it.

Texts are read once: they become blocks of small integers beside the 64-bit hashes
of the words they stand for, and blocks of a task make up chunks. Level by level, each chunk sends the
runs that it holds with their counts, as arrays, and gets back their counts in the corpus in the same order, so
that no task holds the whole model. A run that only one training document holds once is not
sent back: where its document asks for it, its count is one.
Only bit maps of fixed size are broadcast. They save rows that could not
match; a false hit costs time and changes nothing.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blobs, fold, map_batches, materialize, release_shuffles, sized, text_of

FOLDS, SUPPORT, DEPTH, GAIN, ADD = 10, 100, 2, 0.01, 0.1
CHUNK_BYTES = 8 << 20
BLOCK, PART = 1 << 17, 1_500_000  # tokens of a block, and about those of a range of codes whose counts are settled at a time
FEW = 1_000_000  # retained contexts that are broadcast, 16 MB
BATCH = 2 << 20  # bytes of the arrays that a task sends on at once
SPREAD = 128
VOCABULARY, SLICE = 1 << 16, 4 << 20  # distinct words of a block, bytes of a long text split at once
BITS = 23
END = b"\n"  # no word holds a line feed
_P1, _P2, _P3, _P4, _P5 = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
_GAP = b" \t\n\x0b\x0c\r"


def _hash_long(x: np.ndarray, seed) -> np.ndarray:
    turn = lambda v, k: (v << np.uint64(k)) | (v >> np.uint64(64 - k))
    h = (seed + _P5 + np.uint64(8)) ^ (turn(x * _P2, 31) * _P1)
    h = turn(h, 27) * _P1 + _P4
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def code_of(ctx: np.ndarray, up: np.ndarray) -> np.ndarray:
    """The code of a run of words from those of the run without its last and without its first word, as Spark's xxhash64 gives it."""
    return _hash_long(up, _hash_long(ctx, np.array([42], np.uint64)))


def longer(codes: np.ndarray) -> np.ndarray:
    """Codes of the runs of one word more that end at each token; the first has no meaning."""
    return np.concatenate([codes[:1], code_of(codes[:-1], codes[1:])])


def bit_map(codes: DataFrame) -> np.ndarray:
    """A bit per leading BITS bits of the column ``code``; 2**BITS / 64 rows at most reach the driver."""
    at = codes.select(F.shiftrightunsigned("code", 64 - BITS).alias("at"))
    rows = at.groupBy(F.shiftright("at", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, cast(at & 63 as int)))").alias("bits")).toArrow()
    out = np.zeros(1 << (BITS - 6), np.uint64)
    out[rows.column("word").to_numpy()] = rows.column("bits").to_numpy().view(np.uint64)
    return out


def in_map(bits: np.ndarray, codes: np.ndarray) -> np.ndarray:
    at = codes >> np.uint64(64 - BITS)
    return (bits[(at >> np.uint64(6)).view(np.int64)] >> (at & np.uint64(63))) & np.uint64(1) != 0


# blocks


class _Vocabulary(dict):
    """Words to small integers, in order of appearance."""

    def __missing__(self, word: bytes) -> int:
        i = self[word] = len(self)
        return i


def words_of(text: bytes) -> Iterator[list[bytes]]:
    """The words (A-Z lowered) of a text and its end, a long text slice by slice."""
    at = 0
    while len(text) - at > SLICE:
        cut = at + SLICE
        while cut < len(text) and text[cut] not in _GAP:
            cut += 1
        yield text[at:cut].lower().split()
        at = cut
    last = (text[at:] if at else text).lower().split()
    last.append(END)
    yield last


class _Blocks:
    """Cuts the texts of a task into blocks; a text that passes a block's end goes on in the next, led by its last ``depth`` words."""

    def __init__(self, task: int, depth: int, chunk_bytes: int, block: int):
        import xxhash

        self.hash, self.task, self.depth, self.chunk_bytes, self.block = xxhash.xxh64_intdigest, task, depth, chunk_bytes, block
        self.rows, self.bytes, self.no, self.done = 0, 0, 0, []
        self._open()

    def _open(self) -> None:
        self.words, self.ids, self.pieces, self.n = _Vocabulary(), [], [], 0

    def _put(self, words: list[bytes]) -> None:
        self.ids.append(np.fromiter(map(self.words.__getitem__, words), np.uint16, len(words)))
        self.n += len(words)

    def close(self) -> None:
        if self.n:
            hashes = np.fromiter((self.hash(w, 0) for w in self.words), np.uint64, len(self.words))
            p = np.array(self.pieces, np.int64)
            train = int((p[:, 4] - p[:, 3])[p[:, 2] & 1 == 0].sum())
            self.no += 1
            self.done.append(((self.task << 24) + self.bytes // self.chunk_bytes, self.no, train, self.n, np.concatenate(self.ids).tobytes(), hashes.tobytes(), p.tobytes()))
        self._open()

    def add(self, doc, held: bool, text: bytes) -> None:
        row, self.rows = (self.task << 40) + self.rows, self.rows + 1
        flags, tail = int(held) + 2 * (doc is None), []
        for words in words_of(text):
            at = 0
            while at < len(words):
                room = min(VOCABULARY - len(self.words), self.block - self.n) - self.depth
                if room <= 0:
                    self.close()
                    continue
                part = words if not at and len(words) <= room else words[at : at + room]
                before = self.n
                if tail:
                    self._put(tail)
                self._put(part)
                self.pieces.append((row, doc or 0, flags, len(tail), self.n - before))
                at += len(part)
                tail = [*tail, *part[-self.depth :]][-self.depth :] if self.depth else []
        self.bytes += len(text)


def blocks_of(docs: DataFrame, id_col: str, text_col: str, depth: int, chunk_bytes: int, block: int = BLOCK) -> DataFrame:
    """(chunk, no, train, tokens, ids, vocab, pieces): the texts as blocks, numbered in a task, written down.

    A piece is (row, doc_id, flags, lead, tokens): flag 1 is held out, 2 a null identifier; ``lead`` of its tokens belong to an earlier piece of the row.
    """

    def run(batches):
        from pyspark import TaskContext

        cut = _Blocks(TaskContext.get().partitionId(), depth, chunk_bytes, block)

        def out():
            c = list(zip(*cut.done))
            cut.done = []
            return pa.record_batch([*(pa.array(x, pa.int64()) for x in c[:4]), *(pa.array(x, pa.binary()) for x in c[4:])], ["chunk", "no", "train", "tokens", "ids", "vocab", "pieces"])

        for b in batches:
            for doc, held, text in zip(b.column("doc_id").to_pylist(), b.column("held").to_pylist(), blobs(b.column("text"))):
                cut.add(doc, held, text)
                if len(cut.done) >= 8:
                    yield out()
        cut.close()
        if cut.done:
            yield out()

    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), (fold(F.col(id_col), FOLDS) == 0).alias("held"), text_of(text_col).cast("binary").alias("text"))
    return materialize(map_batches(base, run, "chunk long, no long, train long, tokens long, ids binary, vocab binary, pieces binary"), compression="zstd")


@dataclass
class _Block:
    """A block read back: word hashes, word numbers, pieces; per token its place in the document, whether it is the piece's own, and whether its row is training text."""

    vocab: np.ndarray
    ids: np.ndarray
    pieces: np.ndarray
    place: np.ndarray
    own: np.ndarray
    train: np.ndarray


def _read(ids: bytes, vocab: bytes, pieces: bytes) -> _Block:
    p = np.frombuffer(pieces, np.int64).reshape(-1, 5)
    n = p[:, 4]
    place = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    return _Block(np.frombuffer(vocab, np.uint64), np.frombuffer(ids, np.uint16), p, place, place >= np.repeat(p[:, 3], n), np.repeat(p[:, 2] & 1 == 0, n))


# counts


class _Counts:
    """Runs by 64-bit code, each with its two shorter codes, its count in training text and whether held-out text has it; merged when the buffer is full."""

    def __init__(self, limit: int = 1_000_000):
        self.parts, self.n, self.limit = [], 0, limit

    def add(self, code: np.ndarray, ctx: np.ndarray, up: np.ndarray, n: np.ndarray, held: np.ndarray) -> None:
        self.parts.append((code, ctx, up, n.astype(np.int32), held.astype(bool)))
        self.n += len(code)
        if self.n > self.limit:
            self.settle()
            self.limit = max(self.limit, 2 * self.n)

    def settle(self) -> tuple[np.ndarray, ...]:
        columns = [np.concatenate(c) for c in zip(*self.parts)]
        self.parts = []
        order = np.argsort(columns[0], kind="stable")
        codes = columns[0][order]
        first = np.flatnonzero(np.r_[True, codes[1:] != codes[:-1]]) if len(codes) else np.zeros(0, np.int64)
        at = order[first]
        out = (codes[first], columns[1][at], columns[2][at], np.add.reduceat(columns[3][order], first, dtype=np.int32) if len(first) else columns[3], np.logical_or.reduceat(columns[4][order], first) if len(first) else columns[4])
        self.parts, self.n = [out], len(first)
        return out


_BLOCK = ["chunk", "no", "ids", "vocab", "pieces"]


def _each_block(batches) -> Iterator[tuple[int, int, _Block]]:
    """(chunk, number, block) of a task's blocks, in order."""
    for b in batches:
        for c, no, *arrays in zip(b.column("chunk").to_pylist(), b.column("no").to_pylist(), *(blobs(b.column(k)) for k in _BLOCK[2:])):
            yield c, no, _read(*arrays)


def _share(codes: np.ndarray, n: int) -> np.ndarray:
    """Each code's place among n equal ranges."""
    return (((codes >> np.uint64(32)) * np.uint64(n)) >> np.uint64(32)).astype(np.int64)


def part_of(ctx: np.ndarray, up: np.ndarray, depth: int, parts: int) -> np.ndarray:
    """The part that settles a run: words by their code, longer runs by their context, which one in SPREAD parts share by the last words, so that a context of any size stays a bounded multiple of a part."""
    if not depth:
        return _share(up, parts)
    spread = -(-parts // SPREAD)
    return (_share(ctx, parts) + _share(up, spread) * (parts // spread)) % parts


def _add_runs(total: _Counts, k: _Block, depth: int, allowed) -> None:
    """The runs of depth + 1 words of a block whose context may be in the bit map; of single words ``up`` is the word and ``ctx`` 0."""
    if not depth:
        n, held = (np.bincount(k.ids[k.own & t], minlength=len(k.vocab)) for t in (k.train, ~k.train))
        seen = n + held > 0
        total.add(k.vocab[seen], np.zeros(int(seen.sum()), np.uint64), k.vocab[seen], n[seen], held[seen])
        return
    h = k.vocab[k.ids]
    for _ in range(depth - 1):
        h = longer(h)
    i = np.flatnonzero((k.place >= depth) & k.own)
    i = i[in_map(allowed, h[i - 1])]
    total.add(code_of(h[i - 1], h[i]), h[i - 1], h[i], k.train[i], ~k.train[i])


def _arranged(total: _Counts, depth: int, parts: int) -> list[np.ndarray]:
    """Part, code, ctx, up, n, held of the runs, by part and context; the order depends on nothing but the set of runs."""
    columns = total.settle()
    to = part_of(columns[1], columns[2], depth, parts)
    order = np.lexsort((columns[1], to))  # equal contexts side by side take less room
    return [c[order] for c in (to, *columns)]


def _asks(blocks: DataFrame, depth: int, allowed, parts: int) -> DataFrame:
    """(part, chunk, first, blocks, ctx, up, n, held): the runs of each chunk as arrays, a row for each part; ``first`` and ``blocks`` say which blocks they come from, should two tasks read a chunk."""

    def run(batches):
        held = allowed.value if allowed is not None else None

        def out(chunk, first, blocks, total):
            if not total.parts:
                return
            to, _, *columns = _arranged(total, depth, parts)
            cuts = np.searchsorted(to, np.arange(parts + 1))
            rows, size = [], 0
            filled = np.flatnonzero(np.diff(cuts))
            for part in filled:
                at = slice(cuts[part], cuts[part + 1])
                rows.append((int(part), chunk, first, blocks, *(c[at].tobytes() for c in columns)))
                size += 21 * (at.stop - at.start)
                if size > BATCH or part == filled[-1]:
                    c = list(zip(*rows))
                    rows, size = [], 0
                    yield pa.record_batch([pa.array(c[0], pa.int32()), *(pa.array(x, pa.int64()) for x in c[1:4]), *(pa.array(x, pa.binary()) for x in c[4:])], ["part", "chunk", "first", "blocks", "ctx", "up", "n", "held"])

        chunk, first, n, total = None, 0, 0, _Counts()
        for c, no, k in _each_block(batches):
            if c != chunk or no != first + n:
                yield from out(chunk, first, n, total)
                chunk, first, n, total = c, no, 0, _Counts()
            n += 1
            _add_runs(total, k, depth, held)
        yield from out(chunk, first, n, total)

    return map_batches(blocks.select(*_BLOCK), run, "part int, chunk long, first long, blocks long, ctx binary, up binary, n binary, held binary")


def _small(n: np.ndarray) -> tuple[bytes, bytes]:
    """Counts as bytes, those of 255 and more beside them."""
    return np.minimum(n, 255).astype(np.uint8).tobytes(), n[n >= 255].tobytes()


def _whole(small: bytes, big: bytes) -> np.ndarray:
    n = np.frombuffer(small, np.uint8).astype(np.int64)
    n[n == 255] = np.frombuffer(big, np.int64)
    return n


def _answers(asks: DataFrame, depth: int, least: int) -> DataFrame:
    """(chunk, first, blocks, part, n, big, ctx, up, kinds): for every chunk the corpus counts of the runs it asked for, in the order of its asking, written down.

    Runs counted fewer than ``least`` times, but for those that held-out text asks
    for too, are answered with 0. A row without a chunk has each other run of its part once, with ctx, up and n, and in
    ``kinds`` the number of all runs of training text.
    """

    def run(t: pa.Table) -> pa.Table:
        ids = [t.column(c).to_pylist() for c in ("chunk", "first", "blocks", "part")]
        ctx, up = (np.frombuffer(b"".join(blobs(t.column(c).combine_chunks())), np.uint64) for c in ("ctx", "up"))
        each = blobs(t.column("n").combine_chunks())
        n, held = np.frombuffer(b"".join(each), np.int32), np.frombuffer(b"".join(blobs(t.column("held").combine_chunks())), bool)
        code = code_of(ctx, up) if depth else up
        order = np.argsort(code, kind="stable")
        inside = code[order]
        start = np.flatnonzero(np.r_[True, inside[1:] != inside[:-1]])
        total, asked = np.add.reduceat(n[order].astype(np.int64), start), np.logical_or.reduceat(held[order], start)
        stay = (total >= least) | ((total > 0) & asked)
        sums = np.empty(len(code), np.int64)
        sums[order] = np.repeat(np.where(stay, total, 0), np.diff(np.append(start, len(code))))
        once = order[start][stay]
        once = once[np.argsort(ctx[once], kind="stable")]
        rows, lo = [(None, None, None, None, sums[once].tobytes(), None, ctx[once].tobytes(), up[once].tobytes(), int((total > 0).sum()))], 0
        for *i, x in zip(*ids, each):
            at = slice(lo, lo + len(x) // 4)
            lo = at.stop
            rows.append((*i, *_small(sums[at]), None, None, None))
        c = list(zip(*rows))
        return pa.table([*(pa.array(x, pa.int64()) for x in c[:3]), pa.array(c[3], pa.int32()), *(pa.array(x, pa.binary()) for x in c[4:8]), pa.array(c[8], pa.int64())], ["chunk", "first", "blocks", "part", "n", "big", "ctx", "up", "kinds"])

    out = materialize(asks.groupBy("part").applyInArrow(run, "chunk long, first long, blocks long, part int, n binary, big binary, ctx binary, up binary, kinds long"), compression="zstd")
    release_shuffles(asks.sparkSession)
    return out


def _runs(answers: DataFrame, depth: int, least: int) -> DataFrame:
    """(code, ctx, up, n) of the runs counted ``least`` times or more, a row each."""

    def run(batches):
        for b in batches:
            for up, n, ctx in zip(*(blobs(b.column(k)) for k in ("up", "n", "ctx"))):
                n = np.frombuffer(n, np.int64)
                i = np.flatnonzero(n >= least)
                up, ctx, n = np.frombuffer(up, np.uint64)[i], np.frombuffer(ctx, np.uint64)[i], n[i]
                code = code_of(ctx, up) if depth else up
                for lo in range(0, len(i), 100_000):
                    yield pa.record_batch([pa.array(x[lo : lo + 100_000].view(np.int64)) for x in (code, ctx, up, n)], ["code", "ctx", "up", "n"])

    return map_batches(answers.filter("chunk is null").select("up", "n", "ctx"), run, "code long, ctx long, up long, n long")


def _retained(grams: DataFrame, contexts: DataFrame, suffixes: DataFrame, gain: float) -> DataFrame:
    """(code, total, kinds) of the contexts that stay, written down.

    grams: (ctx, up, n) counted twice or more; contexts: (ctx, total); suffixes: (up, m, all), counts of the same
    word after the suffix and of the suffix. Every occurrence is rated by the counts of its
    context without itself, smoothed as in scoring, against the suffix; what
    is seen once rates alike whatever the word. The mean gain has to pass ``gain``
    nats, and the sum four deviations of its noise.
    """
    rows = grams.groupBy("ctx").agg(F.sum("n").alias("twice"), F.count("*").alias("types"))
    sizes = sized(materialize(rows.join(contexts, "ctx").select("ctx", "total", (F.col("types") + F.col("total") - F.col("twice")).alias("kinds"), (F.col("total") - F.col("twice")).alias("once"))))
    p = F.col("m") / F.col("all")
    own = (F.col("n") - 1 + F.col("kinds") * p) / (F.col("total") - 1 + F.col("kinds"))
    rated = grams.join(suffixes, "up").join(sizes, "ctx").withColumn("l", F.ln(own / p))  # the shuffled side stays narrow
    each = rated.groupBy("ctx").agg(F.first("total").alias("total"), F.first("kinds").alias("kinds"), F.first("once").alias("once"), F.sum(F.col("n") * F.col("l")).alias("div"), F.sum(F.col("n") * F.col("l") * F.col("l")).alias("square"))
    single = F.ln(F.col("kinds") / (F.col("total") - 1 + F.col("kinds")))
    each = each.withColumn("div", F.col("div") + F.col("once") * single).withColumn("square", F.col("square") + F.col("once") * single * single)
    noise = F.sqrt(F.greatest(F.col("square") - F.col("div") * F.col("div") / F.col("total"), F.lit(0.0)))
    return materialize(each.filter((F.col("div") >= gain * F.col("total")) & (F.col("div") > 4 * noise)).select(F.col("ctx").alias("code"), "total", "kinds"))


@dataclass
class SuffixTree:
    """Size of the training words, and a bit map of the retained contexts' codes."""

    words: int
    distinct: int
    depth: int
    contexts: np.ndarray

    def root(self, c: np.ndarray) -> np.ndarray:
        return (c + ADD) / (self.words + ADD * (self.distinct + 1))


def _grow(blocks: DataFrame, support: int, depth: int, gain: float, least: int) -> tuple[SuffixTree, list[DataFrame], list[DataFrame], list, int]:
    """The tree's size, the answers of each level (words, pairs, ...), the retained contexts of one word, two words, ..., and the levels' bit maps and number of parts."""
    spark = blocks.sparkSession
    words, tokens = blocks.agg(F.coalesce(F.sum("train"), F.lit(0)), F.coalesce(F.sum("tokens"), F.lit(0))).collect()[0]
    parts = max(1, math.ceil(tokens / PART))
    answers, kept, maps = [_answers(_asks(blocks, 0, None, parts), 0, least)], [], [None]
    distinct = answers[0].agg(F.coalesce(F.sum("kinds"), F.lit(0))).collect()[0][0]
    bits = np.zeros(1 << (BITS - 6), np.uint64)
    for d in range(1, depth + 1):
        frequent = _runs(answers[-1], d - 1, support)
        allowed = bit_map(frequent)
        if not allowed.any():
            break
        maps.append(spark.sparkContext.broadcast(allowed))
        answers.append(_answers(_asks(blocks, d, maps[d], parts), d, least))
        suffixes = _runs(answers[-2], d - 1, 2).select(F.col("code").alias("up"), F.col("n").alias("m"), "ctx")
        if d == 1:
            suffixes = suffixes.select("up", "m", F.lit(int(words)).alias("all"))
        else:
            above = _runs(answers[-3], d - 2, support).select(F.col("code").alias("ctx"), F.col("n").alias("all"))
            suffixes = suffixes.join(sized(above), "ctx").select("up", "m", "all")
        kept.append(_retained(_runs(answers[-1], d, 2).select("ctx", "up", "n"), frequent.select(F.col("code").alias("ctx"), F.col("n").alias("total")), suffixes, gain))
        bits |= bit_map(kept[-1])
    return SuffixTree(int(words), int(distinct), depth, bits), answers, kept, maps, parts


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", support: int = SUPPORT, depth: int = DEPTH, gain: float = GAIN, chunk_bytes: int = CHUNK_BYTES) -> tuple[SuffixTree, DataFrame]:
    """The tree's size and the table (code, n, total, kinds), from documents of folds other than 0, for scoring other documents too.

    A row with ``n`` counts a word or a retained context's next word, a row with ``total`` is a retained context.
    """
    tree, answers, kept, *_ = _grow(blocks_of(docs, id_col, text_col, depth, chunk_bytes), support, depth, gain, 1)
    none = F.lit(0).cast("long")
    table = _runs(answers[0], 0, 1).select("code", "n", none.alias("total"), none.alias("kinds"))
    for d, (a, k) in enumerate(zip(answers[1:], kept), 1):
        table = table.union(_runs(a, d, 1).join(k.select(F.col("code").alias("ctx")), "ctx", "left_semi").select("code", "n", none, none)).union(k.select("code", none, "total", "kinds"))
    return tree, table


# scoring


def _wanted(blocks: DataFrame, tree: SuffixTree, contexts_only: bool) -> DataFrame:
    """(chunk, code): the runs of each chunk that may be retained contexts, or all that may be in a tree of other documents; once in each task that reads the chunk."""
    held = blocks.sparkSession.sparkContext.broadcast(tree)

    def run(batches):
        tree = held.value

        def out(chunk, codes):
            every = np.unique(np.concatenate(codes)) if codes else np.zeros(0, np.uint64)
            for at in range(0, len(every), 100_000):
                part = every[at : at + 100_000]
                yield pa.record_batch([pa.array(np.full(len(part), chunk, np.int64)), pa.array(part.view(np.int64))], ["chunk", "code"])

        chunk, codes = None, []
        for c, _, k in _each_block(batches):
            if c != chunk:
                yield from out(chunk, codes)
                chunk, codes = c, []
            h = k.vocab[k.ids]
            codes.append(k.vocab[in_map(tree.contexts, k.vocab)] if contexts_only else k.vocab)
            for d in range(1, tree.depth + 1 - contexts_only):
                run = longer(h)
                if not contexts_only:
                    i = np.flatnonzero((k.place >= d) & k.own)
                    codes.append(run[i[in_map(tree.contexts, h[i - 1])]])
                h = run
                codes.append(np.unique(h[(k.place >= d) & in_map(tree.contexts, h)]))
        yield from out(chunk, codes)

    return map_batches(blocks.select(*_BLOCK), run, "chunk long, code long")


class _Table:
    """A chunk's answers: counts and, for retained contexts, kinds of next words."""

    def __init__(self, code: np.ndarray, n: np.ndarray, kinds: np.ndarray):
        order = np.argsort(code.view(np.uint64), kind="stable")
        code = code.view(np.uint64)[order]
        start = np.flatnonzero(np.r_[True, code[1:] != code[:-1]]) if len(code) else np.zeros(0, np.int64)
        most = lambda v: np.maximum.reduceat(v[order].astype(float), start) if len(start) else np.zeros(0)
        self.code, self.n, self.kinds = code[start], most(n), most(kinds)

    def find(self, asked: np.ndarray) -> np.ndarray:
        """Row of each code, or -1."""
        if not len(self.code):
            return np.full(len(asked), -1)
        once, back = np.unique(asked, return_inverse=True)
        at = np.searchsorted(self.code, once)
        at[at == len(self.code)] = 0
        return np.where(self.code[at] == once, at, -1)[back]

    def at(self, values: np.ndarray, rows: np.ndarray, otherwise) -> np.ndarray:
        return np.where(rows >= 0, values[rows], otherwise) if len(values) else np.broadcast_to(otherwise, len(rows)).astype(float)


def _rated(tree: SuffixTree, table: _Table, k: _Block, within: bool) -> np.ndarray:
    """Per piece: tokens, known tokens, log10 probabilities by unigrams and by the tree."""
    single = (k.train if within else np.zeros(len(k.ids), bool)).astype(float)
    words = table.find(k.vocab)
    c = np.where(words[k.ids] >= 0, table.at(table.n, words, 0.0)[k.ids], single)
    p = tree.root(c)
    base = np.log10(p)
    kinds, totals = table.at(table.kinds, words, 0.0)[k.ids], table.at(table.n, words, 0.0)[k.ids]
    h = k.vocab[k.ids]
    for d in range(1, tree.depth + 1):
        i = np.flatnonzero((k.place >= d) & k.own)
        i = i[kinds[i - 1] > 0]
        run = longer(h)
        n, t = table.at(table.n, table.find(run[i]), single[i]), totals[i - 1]
        p[i] = (n + kinds[i - 1] * p[i]) / (t + kinds[i - 1])
        if d < tree.depth:
            kinds, totals = np.zeros(len(h)), np.zeros(len(h))
            may = np.flatnonzero((k.place >= d) & in_map(tree.contexts, run))
            rows = table.find(run[may])
            kinds[may], totals[may] = table.at(table.kinds, rows, 0.0), table.at(table.n, rows, 0.0)
            h = run
    start = np.cumsum(k.pieces[:, 4]) - k.pieces[:, 4]
    sums = lambda v: np.add.reduceat(np.where(k.own, v, 0.0), start)
    return np.stack([sums(1.0), sums((c > 0).astype(float)), sums(base), sums(np.log10(p))])


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chunk_bytes: int = CHUNK_BYTES, model: tuple[SuffixTree, DataFrame] | None = None, support: int = SUPPORT, depth: int = DEPTH, gain: float = GAIN, block: int = BLOCK, few: int = FEW) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Without ``model`` the tree is grown from the documents of folds other than 0
    of the same table. Null texts are empty (the end alone); a null identifier hashes
    as ''; repeated rows each get their row; a very long text is cut into pieces whose contexts reach back over the cut. With no training document every count is 0. An empty
    table gives an empty result. Extra columns are ignored.
    """
    blocks = blocks_of(docs, id_col, text_col, model[0].depth if model else depth, chunk_bytes, block)
    known = None  # the retained contexts, if they are few; else each chunk gets its own by a join
    null, none, zero = (lambda kind: F.lit(None).cast(kind)), F.lit(None).cast("long"), F.lit(0).cast("long")
    alone = lambda df: df.select("chunk", null("int").alias("depth"), none.alias("first"), none.alias("blocks"), null("int").alias("part"), null("binary").alias("n"), null("binary").alias("big"), "code", "single", "kinds")
    if model:
        tree, table = model
        maps, size = [], 0
        rows = alone(_wanted(blocks, tree, False).join(table.select("code", F.greatest("n", "total").alias("single"), "kinds"), "code"))
    else:
        tree, answers, kept, maps, size = _grow(blocks, support, depth, gain, 2)
        parts = [a.filter("chunk is not null").select("chunk", F.lit(d).alias("depth"), "first", "blocks", "part", "n", "big", none.alias("code"), none.alias("single"), none.alias("kinds")) for d, a in enumerate(answers)]
        contexts = functools.reduce(DataFrame.union, [k.select("code", "kinds") for k in kept]) if kept else None
        if contexts is not None and contexts.count() <= few:
            table = contexts.toArrow()  # at most ``few`` rows of 16 bytes
            table = table.column("code").to_numpy().view(np.uint64), table.column("kinds").to_numpy()
            order = np.argsort(table[0])
            known = blocks.sparkSession.sparkContext.broadcast(tuple(c[order] for c in table))
        elif contexts is not None:
            parts.append(alone(_wanted(blocks, tree, True).join(contexts, "code").withColumn("single", zero)))
        rows = functools.reduce(DataFrame.union, parts)
    held, within = blocks.sparkSession.sparkContext.broadcast(tree), model is None

    def rate(key, texts, rows):
        tree = held.value
        own = {no: _read(*arrays) for no, *arrays in zip(texts.column("no").to_pylist(), *(blobs(texts.column(k).combine_chunks()) for k in _BLOCK[2:]))}
        single = rows.filter(pc.is_valid(rows.column("code")))
        codes, ns, kinds = ([single.column(c).to_numpy().astype(np.int64)] for c in ("code", "single", "kinds"))
        groups: dict[tuple, list] = {}
        asked = rows.filter(pc.is_valid(rows.column("depth")))
        for d, first, n, part, *counts in zip(*(asked.column(c).to_pylist() for c in ("depth", "first", "blocks", "part", "n", "big"))):
            groups.setdefault((d, first, n), []).append((part, *counts))
        for (d, first, n), answers in groups.items():
            total = _Counts()
            for no in range(first, first + n):
                _add_runs(total, own[no], d, maps[d].value if d else None)
            codes.append(_arranged(total, d, size)[1].view(np.int64))
            ns.append(np.concatenate([_whole(*x) for _, *x in sorted(answers)]))
            kinds.append(np.zeros(len(codes[-1]), np.int64))
        code, n = np.concatenate(codes), np.concatenate(ns)
        sent = (n > 0) | (np.arange(len(n)) < len(codes[0]))  # 0 is the answer for runs that were left out
        code, n, kinds = code[sent].view(np.uint64), n[sent], np.concatenate(kinds)[sent]
        if known is not None and len(known.value[0]):
            at = np.minimum(np.searchsorted(known.value[0], code), len(known.value[0]) - 1)
            kinds = np.where(known.value[0][at] == code, known.value[1][at], kinds)
        table = _Table(code, n, kinds)
        out = [(k.pieces, _rated(tree, table, k, within)) for _, k in sorted(own.items())]
        p, s = np.concatenate([x for x, _ in out]), np.concatenate([x for _, x in out], axis=1)
        return pa.table([pa.array(p[:, 0]), pa.array(p[:, 1], mask=p[:, 2] & 2 > 0), pa.array(p[:, 2] & 1 > 0), pa.array(s[0].astype(np.int64)), pa.array(s[1].astype(np.int64)), pa.array(s[2]), pa.array(s[3])], ["row", "doc_id", "held_out", "n_tokens", "n_known", "base_score", "score"])

    rated = blocks.select(*_BLOCK).groupBy("chunk").cogroup(rows.groupBy("chunk")).applyInArrow(rate, "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    each = rated.groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.first("held_out").alias("held_out"), *[F.sum(c).alias(c) for c in ("n_tokens", "n_known", "base_score", "score")])
    return each.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(tree.words).cast("long").alias("train_tokens"), "base_score", "score")
