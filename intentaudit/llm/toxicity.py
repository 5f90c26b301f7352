"""Toxic spans by a linear-chain conditional random field.

Only documents carry labels, so tokens are labelled first: in a toxic
document, a token counts as toxic if its word or its beginning is far more frequent in
toxic than in clean documents of the training sample. A two-state chain is
fitted on windows of these tokens; its forward-backward marginals give offending offsets
and, through a logistic calibration on documents set aside, the document score.
"""

from __future__ import annotations

import math
import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blobs, bounded_sample, fold, map_batches, materialize, text_of

SPACE = 1 << 18
SAMPLE, FOLDS = 3000, 5  # labelled documents per class
TAGGED, OTHERS = 12, 6  # training windows of a document: around tagged tokens, and anywhere, both by hash
CELLS, LONG = 1 << 20, 1 << 12  # padded cells of a batch of texts, tokens of a text beyond which it is solved in blocks
WINDOW, EPOCHS, RATE, DECAY = 15, 4, 0.3, 1e-4
_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_EDGE = re.compile(r"^[\W_]+|[\W_]+$")


def word_features(word: str) -> list[int]:
    """Hashed identity, beginnings and ending of a word without edge punctuation."""
    w = _EDGE.sub("", word.lower())
    if not w:
        return [0, 0, 0, 0]
    return [zlib.crc32(x.encode("utf-8", "replace")) % SPACE for x in (f"w{w}", f"5{w[:5]}", f"4{w[:4]}", f"e{w[-3:]}")]


class _Features(dict):
    def __missing__(self, w):
        if len(self) > 300_000:
            self.clear()
        f = self[w] = word_features(w)
        return f


@dataclass
class SpanModel:
    weights: np.ndarray  # per feature, state 1 against 0
    bias: float
    trans: np.ndarray  # 2x2 log scores
    cal: np.ndarray  # logistic weights over document measures

    def emission(self, word: str) -> float:
        return float(self.weights[word_features(word)].sum() + self.bias)


def marginals(e: np.ndarray, lengths: np.ndarray, trans: np.ndarray) -> np.ndarray:
    """P(state 1) per token for padded rows sorted by descending length, by odds recursions."""
    m = np.exp(trans)
    x = np.exp(np.clip(e, -30, 30))
    rows, steps = e.shape
    active = np.searchsorted(-lengths, -np.arange(steps), side="left")  # rows longer than t
    fwd, bwd = np.zeros_like(x), np.ones_like(x)
    fwd[:, 0] = x[:, 0]
    for t in range(1, steps):
        k = active[t]
        o = fwd[:k, t - 1]
        fwd[:k, t] = np.clip(x[:k, t] * (o * m[1, 1] + m[0, 1]) / (o * m[1, 0] + m[0, 0]), 1e-30, 1e30)
    for t in range(steps - 2, -1, -1):
        k = active[t + 1]
        o = x[:k, t + 1] * bwd[:k, t + 1]
        bwd[:k, t] = np.clip((o * m[1, 1] + m[1, 0]) / (o * m[0, 1] + m[0, 0]), 1e-30, 1e30)
    odds = fwd * bwd
    return odds / (1 + odds)


def long_marginals(e: np.ndarray, trans: np.ndarray) -> np.ndarray:
    """The same for one long row, in about the square root of its length as many steps.

    A block of tokens turns incoming odds into outgoing ones by a 2x2 matrix. All blocks' matrices are
    built side by side, the odds at their edges follow one after the other, and then all blocks are solved side by side.
    """
    n = len(e)
    size = max(1, int(math.sqrt(n)))
    blocks = -(-n // size)
    m = np.exp(trans)
    x = np.ones((blocks, size))
    x.reshape(-1)[:n] = np.exp(np.clip(e, -30, 30))
    live = (np.arange(blocks * size) < n).reshape(blocks, size)

    def product(steps, matrix):
        out = np.tile(np.eye(2), (blocks, 1, 1))
        for t in steps:
            out = np.where(live[:, t, None, None], matrix(t) @ out, out)
            out /= out.sum(axis=(1, 2), keepdims=True)
        return out

    ones = np.ones(blocks)
    # forward (odds, 1) after token t from before it; backward from after token t to before it
    ahead = product(range(size), lambda t: np.stack([np.stack([x[:, t] * m[1, 1], x[:, t] * m[0, 1]], -1), np.stack([ones * m[1, 0], ones * m[0, 0]], -1)], -2))
    back = product(range(size - 1, -1, -1), lambda t: np.stack([np.stack([x[:, t] * m[1, 1], ones * m[1, 0]], -1), np.stack([x[:, t] * m[0, 1], ones * m[0, 0]], -1)], -2))
    clip = lambda v: np.clip(v, 1e-30, 1e30)
    into, after = np.zeros(blocks), np.ones(blocks)
    o = None
    for b in range(blocks):
        if b:
            into[b] = o
            a, c = ahead[b] @ (o, 1.0)
            o = clip(a / c)
        else:  # the first token has no predecessor
            o = x[0, 0]
            for t in range(1, size if blocks > 1 else 0):
                o = clip(x[0, t] * (o * m[1, 1] + m[0, 1]) / (o * m[1, 0] + m[0, 0]))
    for b in range(blocks - 2, -1, -1):
        a, c = back[b + 1] @ (after[b + 1], 1.0)
        after[b] = clip(a / c)
    fwd, bwd = np.zeros_like(x), np.ones_like(x)
    o = into
    for t in range(size):
        step = clip(x[:, t] * (o * m[1, 1] + m[0, 1]) / (o * m[1, 0] + m[0, 0]))
        if t == 0:
            step[0] = x[0, 0]
        fwd[:, t] = o = step
    q = after
    for t in range(size - 1, -1, -1):
        last = live[:, t] & (~live[:, t + 1] if t + 1 < size else True)
        q = np.where(last, after, q)
        bwd[:, t] = q
        r = x[:, t] * q
        q = clip((r * m[1, 1] + m[1, 0]) / (r * m[0, 1] + m[0, 0]))
    odds = (fwd * bwd).reshape(-1)[:n]
    return odds / (1 + odds)


def document_marginals(rows: list[np.ndarray], trans: np.ndarray, cells: int = CELLS, long: int = LONG) -> list[np.ndarray]:
    """Marginals of each text; texts of like length are padded together up to ``cells`` cells, long ones are solved by themselves."""
    order = sorted(range(len(rows)), key=lambda i: -len(rows[i]))
    out: list[np.ndarray] = [np.zeros(0)] * len(rows)
    at = 0
    while at < len(order) and len(rows[order[at]]):
        if (most := len(rows[order[at]])) > long:
            out[order[at]] = long_marginals(rows[order[at]], trans)
            at += 1
            continue
        part = [i for i in order[at : at + max(1, min(128, cells // most))] if len(rows[i])]
        at += len(part)
        lengths = np.array([len(rows[i]) for i in part])
        e = np.zeros((len(part), most))
        for r, i in enumerate(part):
            e[r, : lengths[r]] = rows[i]
        p = marginals(e, lengths, trans)
        for r, i in enumerate(part):
            out[i] = p[r, : lengths[r]]
    return out


def measures(p: np.ndarray) -> np.ndarray:
    """Bias, greatest log odds and log of the expected number of toxic tokens."""
    top = float(np.clip(p.max(), 1e-6, 1 - 1e-6)) if len(p) else 1e-6
    return np.array([1.0, np.log(top / (1 - top)) / 5, np.log1p(float(p[p > 0.1].sum()) if len(p) else 0.0)])


def fit_chain(windows: np.ndarray, tags: np.ndarray, lengths: np.ndarray | None = None, epochs: int = EPOCHS, rate: float = RATE, decay: float = DECAY, seed: int = 1) -> tuple[np.ndarray, float, np.ndarray]:
    """Fit by adaptive gradient steps. windows: rows x tokens x features; tags: rows x tokens; lengths: tokens of each row that count, the rest is padding."""
    rng = np.random.default_rng(seed)
    w, gw = np.zeros(SPACE), np.full(SPACE, 1e-6)
    b, gb, trans, gt = -2.0, 1e-6, np.array([[1.0, -1.0], [0.0, 0.0]]), np.full((2, 2), 1e-6)
    steps = windows.shape[1]
    for _ in range(epochs):
        order = rng.permutation(len(windows))
        for at in range(0, len(order), 256):
            i = order[at : at + 256]
            n = np.full(len(i), steps) if lengths is None else lengths[i]
            i, n = i[np.argsort(-n, kind="stable")], -np.sort(-n, kind="stable")
            live = np.arange(steps) < n[:, None]
            f, y = windows[i], tags[i].astype(float)
            e = w[f].sum(axis=2) + b
            p = marginals(e, n, trans)
            d = np.where(live, p - y, 0.0) / len(i)
            # expected and observed transitions, expected ones by pair marginals
            g = np.zeros((2, 2))
            m, x = np.exp(trans), np.exp(np.clip(e, -30, 30))
            fwd, bwd = np.zeros_like(x), np.ones_like(x)
            fwd[:, 0] = x[:, 0]
            for t in range(1, steps):
                o = fwd[:, t - 1]
                fwd[:, t] = np.clip(x[:, t] * (o * m[1, 1] + m[0, 1]) / (o * m[1, 0] + m[0, 0]), 1e-30, 1e30)
            for t in range(steps - 2, -1, -1):
                o = x[:, t + 1] * bwd[:, t + 1]
                bwd[:, t] = np.where(live[:, t + 1], np.clip((o * m[1, 1] + m[1, 0]) / (o * m[0, 1] + m[0, 0]), 1e-30, 1e30), 1.0)
            o, q = fwd[:, :-1], x[:, 1:] * bwd[:, 1:]
            z = m[0, 0] + m[0, 1] * q + o * m[1, 0] + o * m[1, 1] * q
            for u, v, k in ((0, 0, m[0, 0]), (0, 1, m[0, 1] * q), (1, 0, o * m[1, 0]), (1, 1, o * m[1, 1] * q)):
                seen = ((y[:, :-1] == u) & (y[:, 1:] == v) & live[:, 1:]).sum()
                g[u, v] = (np.where(live[:, 1:], k / z, 0.0).sum() - seen) / len(i)
            gt += g * g
            trans = trans - rate * g / np.sqrt(gt)
            grad = np.zeros(SPACE)
            np.add.at(grad, f.reshape(-1), np.repeat(d.reshape(-1), f.shape[2]))
            hit = np.flatnonzero(grad)
            grad[hit] += decay * w[hit]
            gw[hit] += grad[hit] ** 2
            w[hit] -= rate * grad[hit] / np.sqrt(gw[hit])
            s = d.sum()
            gb += s * s
            b -= rate * s / np.sqrt(gb)
    return w, float(b), trans


def _logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    beta = np.zeros(x.shape[1])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        h = (x * (weight * p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(beta))
        beta = beta + np.clip(np.linalg.solve(h, x.T @ (weight * (y - p)) - ridge * beta), -2, 2)
    return beta


def _chosen(candidates: np.ndarray, n: int, key: str) -> np.ndarray:
    """At most n of the places, by hash of the key and the place."""
    return candidates if len(candidates) <= n else np.array(sorted(candidates, key=lambda i: zlib.crc32(f"{key}:{i}".encode()))[:n])


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> SpanModel:
    """Fit on at most ``sample`` documents per class (the smallest by md5) of folds other than 0, a quarter of them set aside for calibration.

    Their texts, of any length, stay on the executors: word statistics, training windows (a bounded
    number per document, shorter for texts shorter than a window) and calibration measures are computed there. Without a
    labelled document, or without words in them, the score is constant.
    """
    spark = docs.sparkSession
    known = labels.filter(F.col("toxic").isNotNull() & (fold(F.col("doc_id"), FOLDS) != 0)).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).dropDuplicates(["doc_id"])
    prior = known.agg(F.avg("toxic")).collect()[0][0]
    flat = lambda cal: SpanModel(np.zeros(SPACE), -2.0, np.zeros((2, 2)), np.array(cal))
    if prior is None:
        return flat([-3.0, 1.0, 1.0])
    constant = [np.log(max(prior, 1e-3) / max(1 - prior, 1e-3)), 0.0, 0.0]
    chosen = bounded_sample(known.filter("toxic = 1"), sample, "tox", "doc_id").union(bounded_sample(known.filter("toxic = 0"), sample, "tox", "doc_id"))
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")).join(F.broadcast(chosen), "doc_id")
    rows = materialize(texts.select("doc_id", "text", "toxic").dropDuplicates(["doc_id"]))
    aside = lambda doc: zlib.crc32(f"cal{doc}".encode()) % 4 == 0

    def statistics(batches):
        """(class, feature, documents): how many training documents of a class have a word or beginning; feature -1 counts the documents."""
        feats, df, n = _Features(), np.zeros((2, SPACE), np.int64), [0, 0]
        for b in batches:
            for doc, text, y in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text", "toxic"))):
                if not aside(doc):
                    found = {x for w in set(_WORD.findall(text)) for x in feats[w][:2]}
                    df[y][np.fromiter(found, np.int64, len(found))] += 1
                    n[y] += 1
        for y in (0, 1):
            at = np.flatnonzero(df[y])
            yield pa.record_batch([pa.array(np.full(len(at) + 1, y, np.int32)), pa.array(np.append(at, -1).astype(np.int32)), pa.array(np.append(df[y][at], n[y]))], ["toxic", "feature", "n"])

    counts = map_batches(rows, statistics, "toxic int, feature int, n long").groupBy("toxic", "feature").agg(F.sum("n").alias("n")).toArrow()  # at most 2 * SPACE rows
    y, f, c = (counts.column(k).to_numpy() for k in ("toxic", "feature", "n"))
    df, n = np.zeros((2, SPACE)), np.zeros(2)
    df[y[f >= 0], f[f >= 0]] = c[f >= 0]
    n[y[f < 0]] = c[f < 0]
    odds = np.log((df[1] + 0.5) / (n[1] + 1)) - np.log((df[0] + 0.5) / (n[0] + 1))
    toxic_feature = (odds > np.log(12)) & (df[1] >= 4)
    toxic_feature[0] = False
    marks = spark.sparkContext.broadcast(toxic_feature)

    def cut(batches):
        """Windows of tokens' features, their tags and lengths, in documents of the training part."""
        feats = _Features()
        for b in batches:
            out = []
            for doc, text, y in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text", "toxic"))):
                words = [] if aside(doc) else _WORD.findall(text)
                if not words:
                    continue
                f = np.array([feats[w] for w in words], np.int32)
                tag = marks.value[f[:, :2]].any(axis=1) if y else np.zeros(len(f), bool)
                last = max(0, len(f) - WINDOW)
                around = np.clip(_chosen(np.flatnonzero(tag), TAGGED, f"t{doc}") - WINDOW // 2, 0, last)
                rng = np.random.default_rng(zlib.crc32(f"w{doc}".encode()))
                for s in sorted({*around.tolist(), *rng.integers(0, last + 1, OTHERS).tolist()}):
                    part = f[s : s + WINDOW]
                    out.append((doc, np.pad(part, ((0, WINDOW - len(part)), (0, 0))).tobytes(), np.pad(tag[s : s + WINDOW], (0, WINDOW - len(part))).tobytes(), len(part)))
            if out:
                c = list(zip(*out))
                yield pa.record_batch([pa.array(c[0], pa.int64()), pa.array(c[1], pa.binary()), pa.array(c[2], pa.binary()), pa.array(c[3], pa.int32())], ["doc_id", "features", "tags", "size"])

    got = map_batches(rows, cut, "doc_id long, features binary, tags binary, size int").orderBy("doc_id", "features", "tags").toArrow()  # at most 2 * sample * (TAGGED + OTHERS) rows
    if not got.num_rows:
        return flat(constant)
    windows = np.frombuffer(b"".join(blobs(got.column("features").combine_chunks())), np.int32).reshape(-1, WINDOW, 4).astype(np.int64)
    tags = np.frombuffer(b"".join(blobs(got.column("tags").combine_chunks())), bool).reshape(-1, WINDOW)
    w, b, trans = fit_chain(windows, tags, got.column("size").to_numpy().astype(np.int64))
    fitted = spark.sparkContext.broadcast(w.astype(np.float32))

    def measured(batches):
        feats = _Features()
        for batch in batches:
            docs_, texts_, ys = (batch.column(c).to_pylist() for c in ("doc_id", "text", "toxic"))
            words = [_WORD.findall(t) for t in texts_]
            ps = document_marginals([fitted.value[np.array([feats[x] for x in ws], np.int64).reshape(-1, 4)].sum(axis=1) + b for ws in words], trans)
            ms = [measures(p) for p in ps]
            yield pa.record_batch([pa.array(docs_, pa.int64()), *(pa.array([m[k] for m in ms], pa.float64()) for k in range(3)), pa.array(ys, pa.int32()), pa.array([aside(d) for d in docs_], pa.bool_())], ["doc_id", "m0", "m1", "m2", "toxic", "aside"])

    cal = map_batches(rows, measured, "doc_id long, m0 double, m1 double, m2 double, toxic int, aside boolean").orderBy("doc_id").toArrow()  # at most 2 * sample rows
    x, y, held = np.stack([cal.column(f"m{k}").to_numpy() for k in range(3)], axis=1), cal.column("toxic").to_numpy().astype(float), cal.column("aside").to_numpy()
    if held.any():
        x, y = x[held], y[held]
    share = y.mean() if 0 < y.mean() < 1 else 0.5
    weight = np.where(y == 1, prior / share, (1 - prior) / (1 - share))
    return SpanModel(w, b, trans, _logistic(x, y, weight))


def score(docs: DataFrame, model: SpanModel, id_col: str = "doc_id", text_col: str = "text", flag: float = 0.5) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted, n_spans, spans.

    ``spans`` lists start:end (code points) of runs of tokens whose marginal
    reaches ``flag``. Null texts are empty and get the calibrated score of a text
    without toxic token. Repeated rows each get their row, a very long text is solved whole. Labels, language, source and identifier are no inputs of a score.
    An empty table gives an empty result; extra columns are ignored.
    """
    weights, bias, trans, cal = model.weights.astype(np.float32), model.bias, model.trans, model.cal

    class Emissions(dict):
        def __missing__(self, w):
            if len(self) > 300_000:
                self.clear()
            x = self[w] = float(weights[word_features(w)].sum()) + bias
            return x

    def tag(batches):
        known = Emissions()
        for b in batches:
            texts = [t or "" for t in b.column("text").to_pylist()]
            words = [_WORD.findall(t) for t in texts]
            ps = document_marginals([np.fromiter(map(known.__getitem__, w), float, len(w)) for w in words], trans)
            scores, n, spans = [], [], []
            for t, p in zip(texts, ps):
                scores.append(float(1 / (1 + np.exp(-np.clip(measures(p) @ cal, -30, 30)))))
                hot = np.flatnonzero(p >= flag) if len(p) else []
                runs: list[list[int]] = []
                if len(hot):
                    at = [m.span() for m in _WORD.finditer(t)]
                    last = -2
                    for i in hot:
                        if i == last + 1:
                            runs[-1][1] = at[i][1]
                        else:
                            runs.append(list(at[i]))
                        last = i
                n.append(len(runs))
                spans.append(",".join(f"{s}:{e}" for s, e in runs))
            yield pa.record_batch([b.column("doc_id"), b.column("held_out"), pa.array(scores, pa.float64()), pa.array([int(s >= 0.5) for s in scores], pa.int32()), pa.array(n, pa.int64()), pa.array(spans, pa.string())], ["doc_id", "held_out", "score", "predicted", "n_spans", "spans"])

    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), (fold(F.col(id_col), FOLDS) == 0).alias("held_out"), text_of(text_col).alias("text"))
    return map_batches(base, tag, "doc_id long, held_out boolean, score double, predicted int, n_spans long, spans string")
