"""Secret scan: fixed patterns plus credential formats learned by grammar inference.

Credentials found by the patterns in all documents are the labelled examples, of
which each kind's automaton gets a bounded draw by hash. Their prefix tree's states are merged while their outgoing
frequencies are statistically compatible, which gives a probabilistic automaton per
kind; another is learned from ordinary tokens. Every candidate
token of every text is scored by its likelihood under the formats against the ordinary one.
"""

from __future__ import annotations

import hashlib
import heapq
import math
import re
from collections import Counter, deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordIds, blobs, map_batches, materialize, text_of

#: The base patterns, with the least length of what counts.
KINDS = ("assign", "access", "hex")
_ASSIGN = re.compile(rb"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I)
_ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
_HEX = re.compile(rb"[0-9a-f]{24,}")  # runs are maximal, so the bound may stand in the pattern
_KEYWORDS = (b"passw", b"secret", b"token", b"apikey", b"api_key")
_ALPHABET = rb"[A-Za-z0-9+/_.=-]"
_ORDINARY = re.compile(_ALPHABET + rb"{6,}")
EXAMPLES, ALPHA = 500, 0.05


def base_spans(text: bytes) -> list[tuple[int, int, str]]:
    """(start, end, kind) in bytes, by start, then kind as listed."""
    out = []
    low = text.lower()
    if any(k in low for k in _KEYWORDS):
        out += [(m.start(), m.end(), "assign") for m in _ASSIGN.finditer(text) if len(m[2]) >= 6]
    if b"AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in _ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), m.end(), "hex") for m in _HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def symbols(token: bytes) -> str:
    """Character classes: hex letter h, other lower l, upper u, digit d, the rest as they are."""
    return "".join("d" if 48 <= c <= 57 else "h" if 97 <= c <= 102 else "l" if 103 <= c <= 122 else "u" if 65 <= c <= 90 else chr(c) for c in token)


class FormatAutomaton:
    """A probabilistic automaton learned from strings by merging prefix-tree states."""

    def __init__(self, words: list[str], alpha: float = ALPHA):
        self.next: list[dict[str, int]] = [{}]
        self.arrive, self.end, self.via = [0], [0], [Counter()]
        for w in words:
            s = 0
            self.arrive[0] += 1
            for c in w:
                self.via[s][c] += 1
                if c not in self.next[s]:
                    self.next[s][c] = len(self.next)
                    self.next.append({})
                    self.arrive.append(0)
                    self.end.append(0)
                    self.via.append(Counter())
                s = self.next[s][c]
                self.arrive[s] += 1
            self.end[s] += 1
        self._c = math.sqrt(0.5 * math.log(2 / alpha))
        self._merge_all()

    def _differ(self, a: int, na: int, b: int, nb: int) -> bool:
        return na and nb and abs(a / na - b / nb) > self._c * (1 / math.sqrt(na) + 1 / math.sqrt(nb))

    def _compatible(self, p: int, q: int) -> bool:
        todo = [(p, q)]
        while todo:
            a, b = todo.pop()
            na, nb = self.arrive[a], self.arrive[b]
            if self._differ(self.end[a], na, self.end[b], nb):
                return False
            for c in self.via[a].keys() | self.via[b].keys():
                if self._differ(self.via[a][c], na, self.via[b][c], nb):
                    return False
                if c in self.next[a] and c in self.next[b] and (self.next[a][c], self.next[b][c]) != (a, b):
                    todo.append((self.next[a][c], self.next[b][c]))
        return True

    def _fold(self, p: int, q: int) -> None:
        """Add the tree below q to p."""
        todo = [(p, q)]
        while todo:
            a, b = todo.pop()
            self.arrive[a] += self.arrive[b]
            self.end[a] += self.end[b]
            self.via[a].update(self.via[b])
            for c, child in self.next[b].items():
                if c in self.next[a]:
                    todo.append((self.next[a][c], child))
                else:
                    self.next[a][c] = child

    def _merge_all(self) -> None:
        red, seen = [0], {0}
        blue = deque((0, c) for c in sorted(self.next[0]))
        while blue:
            s, c = blue.popleft()
            q = self.next[s][c]
            if q in seen:
                continue
            for p in red:
                if self._compatible(p, q):
                    self.next[s][c] = p
                    self._fold(p, q)
                    blue.extend((p, x) for x in sorted(self.next[p]) if self.next[p][x] not in seen)
                    break
            else:
                red.append(q)
                seen.add(q)
                blue.extend((q, x) for x in sorted(self.next[q]))
        self.states = len(red)

    def score(self, word: str, symbols_: int = 16) -> float:
        """Log probability per symbol, the end counted; unseen steps cost a smoothed share."""
        s, total = 0, 0.0
        for c in word:
            n = self.arrive[s] if s >= 0 else 0
            k = self.via[s][c] if s >= 0 else 0
            total += math.log((k + 1 / symbols_) / (n + 1 + 1 / symbols_))
            s = self.next[s].get(c, -1) if s >= 0 else -1
        n, k = (self.arrive[s], self.end[s]) if s >= 0 else (0, 0)
        total += math.log((k + 1 / symbols_) / (n + 1 + 1 / symbols_))
        return total / (len(word) + 1)


def candidates(text: bytes, spans: list[tuple[int, int, str]], least: int):
    """Tokens of at least ``least`` characters with a digit and a letter outside the base spans."""
    for m in re.finditer(_ALPHABET + b"{%d,}" % least, text):
        w = m[0]
        if not w.isalpha() and not w.isdigit() and re.search(rb"[0-9]", w) and re.search(rb"[A-Za-z]", w) and not any(a < m.end() and m.start() < b for a, b, _ in spans):
            yield m.start(), m.end(), w


class Formats:
    """The learned automata and the least likelihood that counts as a format."""

    def __init__(self, credentials: dict[str, list[bytes]], ordinary: list[bytes]):
        self.models = {k: FormatAutomaton([symbols(w) for w in v]) for k, v in credentials.items() if v}
        self.plain = FormatAutomaton([symbols(w) for w in ordinary] or ["l"])
        self.least = min([16, *(len(w) for v in credentials.values() for w in v)])
        self.floor = {}
        for k, m in self.models.items():
            own = sorted(m.score(symbols(w)) for w in credentials[k])
            self.floor[k] = own[len(own) // 20]
        self.known: dict[str, bool] = {}

    def matches(self, token: bytes) -> bool:
        s = symbols(token)
        hit = self.known.get(s)
        if hit is None:
            p = self.plain.score(s)
            hit = any((x := m.score(s)) >= self.floor[k] and x > p + 0.1 for k, m in self.models.items())
            if len(self.known) > 100_000:
                self.known.clear()
            if len(s) <= 128:
                self.known[s] = hit
        return hit


class _Draw:
    """The distinct words with the smallest hashes, at most ``n``; draws of parts make up the draw of the whole."""

    def __init__(self, n: int):
        self.n, self.held, self.heap, self.edge = n, {}, [], 1 << 64

    def add(self, word: bytes, h: int) -> None:
        if h < self.edge and word not in self.held:
            self.held[word] = h
            heapq.heappush(self.heap, (-h, word))
            if len(self.held) > self.n:
                del self.held[heapq.heappop(self.heap)[1]]
            if len(self.held) == self.n:
                self.edge = -self.heap[0][0]


def learn(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", examples: int = EXAMPLES) -> Formats:
    """Learn from ``examples`` distinct credentials a kind and as many ordinary tokens, drawn by hash from those of all documents."""

    def gather(batches):
        ids, draws = WordIds(), {k: _Draw(examples) for k in (*KINDS, "ordinary")}
        for b in batches:
            for t in blobs(b.column("text")):
                spans = base_spans(t)
                for start, end, kind in spans:
                    w = t[start:end]
                    w = _ASSIGN.fullmatch(w)[2] if kind == "assign" else w
                    draws[kind].add(w, ids[w])
                words = [m[0] for m in _ORDINARY.finditer(t) if not any(a < m.end() and m.start() < b for a, b, _ in spans)] if spans else _ORDINARY.findall(t)
                draw = draws["ordinary"]
                h = ids.array(words)
                for i in (h < np.uint64(min(draw.edge, (1 << 64) - 1))).nonzero()[0].tolist():
                    draw.add(words[i], int(h[i]))
        rows = [(k, w, h - (1 << 63)) for k, d in draws.items() for w, h in d.held.items()]
        yield pa.record_batch([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.int64())], ["kind", "word", "place"])

    found = materialize(map_batches(docs.select(text_of(text_col).cast("binary").alias("text")), gather, "kind string, word binary, place long"))
    words = {k: [bytes(r["word"]) for r in found.filter(F.col("kind") == k).distinct().orderBy("place", "word").limit(examples).collect()] for k in (*KINDS, "ordinary")}
    return Formats({k: words[k] for k in KINDS}, words["ordinary"])


def _points(text: bytes, spans):
    """Byte spans as code points."""
    if text.isascii():
        return spans
    marks = sorted({x for s in spans for x in s[:2]})
    at, n, place = 0, 0, {}
    for m in marks:
        n += len(text[at:m].decode("utf-8", "replace"))
        at, place[m] = m, n
    return [(place[a], place[b], k) for a, b, k in spans]


def scan(docs: DataFrame, formats: Formats | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_format.

    ``spans`` lists kind:start:end of base spans and of tokens with a learned format (kind
    ``format``), by start. Null texts count as empty and have no span; repeated rows
    each get their row. Extra columns are ignored.
    """
    formats = formats or learn(docs, id_col, text_col)

    def find(batches):
        order = (*KINDS, "format")
        for b in batches:
            rows = []
            for t in blobs(b.column("text")):
                base = base_spans(t)
                extra = [(s, e, "format") for s, e, w in candidates(t, base, formats.least) if formats.matches(w)] if formats.models else []
                base = _points(t, base) if base else base
                spans = sorted([*base, *(_points(t, extra) if extra else [])], key=lambda s: (s[0], order.index(s[2])))
                n = Counter(k for *_, k in spans)
                line = lambda ss: ",".join(f"{k}:{s}:{e}" for s, e, k in ss)
                rows.append((n["assign"], n["access"], n["hex"], hashlib.sha256(line(base).encode()).hexdigest(), line(spans), n["format"]))
            c = list(zip(*rows)) or [[]] * 6
            yield pa.record_batch([b.column("doc_id"), *(pa.array(x, pa.int64()) for x in c[:3]), pa.array(c[3], pa.string()), pa.array(c[4], pa.string()), pa.array(c[5], pa.int64())], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_format"])

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).cast("binary").alias("text"))
    return map_batches(texts, find, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_format long")
