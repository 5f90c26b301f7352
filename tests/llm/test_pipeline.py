"""The pipeline against a brute-force version of its stages on the smallest tables."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import xxhash
from tokenizers import Tokenizer

import corpus_pipeline
from intentaudit.llm import mixing, near_dedup, quality

DIR = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    columns, kept = docs.columns, docs
    frames = [docs.cache()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, DIR).cache()
        assert kept.columns == columns, name
        frames.append(kept)
    raw, good, lines, near, mixed = frames
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{DIR}/labels.parquet").collect()}
    assert {r["doc_id"] for r in good.collect()} == brute_quality({r["doc_id"]: r["text"] or "" for r in raw.collect()}, {i for i, q in labels.items() if q == 1})
    seen, want = [], {}
    for r in good.orderBy("doc_id").collect():
        out = []
        for line in (r["text"] or "").split("\n"):
            w = line.lower().encode().split()
            s = {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
            hit = bool(s) and any(4 * len(s & x) >= 3 * len(s | x) for x in seen)
            if s:
                seen.append(s)
            if not hit:
                out.append(line)
        want[r["doc_id"]] = "\n".join(out)
        if (r["text"] or "").split() and not want[r["doc_id"]].split():
            del want[r["doc_id"]]  # nothing is left of it
    got = {r["doc_id"]: r for r in lines.collect()}
    assert {i: r["text"] or "" for i, r in got.items()} == want
    assert all(r["n_chars"] == len(r["text"] or "") for r in got.values())
    sets = {i: near_dedup.exact_shingles(t.encode()) for i, t in want.items()}
    comp = {i: i for i in sets}

    def find(i):
        while comp[i] != i:
            i = comp[i]
        return i

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and near_dedup.similar(sets[a], sets[b]):
                p, q = sorted((find(a), find(b)))
                comp[q] = p
    assert sorted(r["doc_id"] for r in near.collect()) == [i for i in ids if find(i) == i]
    copies = {r["doc_id"]: r["copies"] for r in mixing.mix(near).collect()}
    assert Counter(r["doc_id"] for r in mixed.collect()) == Counter({i: c for i, c in copies.items() if c})
    check_packing(corpus_pipeline.run(spark, DIR).collect(), [(r["doc_id"], r["text"]) for r in mixed.collect()])


def brute_quality(texts, good):
    """Identifiers of the documents with the largest noisy weights, by plain loops over the definition."""
    token, mask = re.compile(rb"[A-Za-z0-9_\x80-\xff]+|[!-/:-@\[-^`{-~]+"), (1 << 64) - 1

    def features(text):
        h = [xxhash.xxh64_intdigest(w, 0) for w in token.findall(text.encode())]
        mix = 0x9E3779B97F4A7C15
        return [x % quality.BUCKETS for x in h] + [(mix if a == b else ((a * mix) & mask) ^ (b >> 7)) % quality.BUCKETS for a, b in zip(h, h[1:])]

    found = {i: Counter(features(t)) for i, t in texts.items()}
    target, raw = Counter(), Counter()
    for i, f in found.items():
        raw.update(f)
        if i in good:
            target.update(f)
    share = lambda c, b: (c[b] + 1) / (sum(c.values()) + quality.BUCKETS)
    ratio = {b: math.log(share(target, b) / share(raw, b)) for b in raw}
    weight = {i: sum(n * ratio[b] for b, n in f.items()) for i, f in found.items()}
    noise = lambda i: -math.log(-math.log((int(hashlib.md5(f"gumbel:{i}".encode()).hexdigest()[:13], 16) + 0.5) / 16**13))
    k = sum(w >= 0 for w in weight.values())
    return set(sorted(weight, key=lambda i: -(weight[i] + noise(i)))[:k])


def check_packing(packed, documents):
    """Every token of every copy lies in one piece, pieces fill sequences without gaps."""
    tok = Tokenizer.from_file(corpus_pipeline.tokenizer_path())
    ids = {(i, t): [*tok.encode(t or "", add_special_tokens=False).ids, 1] for i, t in set(documents)}
    want = Counter()
    for key in documents:
        want.update((key[0], x) for x in ids[key])
    by, seqs, got = {}, {}, Counter()
    for (i, _), x in ids.items():
        by.setdefault(i, []).append(x)
    for r in packed:
        fits = [x for x in by[r["doc_id"]] if len(x) == r["doc_tokens"] and zlib.crc32(np.asarray(x[r["start"] : r["start"] + r["length"]], "<u4").tobytes()) == r["ids_crc32"]]
        assert fits
        got.update((r["doc_id"], x) for x in fits[0][r["start"] : r["start"] + r["length"]])
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert got == want
    for parts in seqs.values():
        end = 0
        for o, n in sorted(parts):
            assert o == end
            end += n
        assert end <= 2048


SCHEMA = "doc_id long, text string, lang string, source string, n_chars int, n_lines string, n_removed int, __gone string, __id string, __key int, __copies int, copies string"


def rows_of_all_kinds():
    rng = random.Random(17)
    say = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 6))) for _ in range(n))
    a, b = say(40), say(40)
    rows = [(5, a), (5, b), (6, a + " more"), (7, b + " more"), (8, a), (9, None), (10, ""), (11, "  \n "), (None, say(30)), (None, say(30)), (None, None), (12, say(3000)), (13, "one two"), (13, "one two")]
    rows += [(20 + i, "\n".join([say(12), "a line that many documents share word for word"])) for i in range(8)]
    return [(i, t, None, s, None if t is None else len(t), "x", 1, "g", "i", 3, 4, "c") for (i, t), s in zip(rows, [None, "s", "t"] * len(rows))]


def write(spark, folder, rows):
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(20 + i, 1, 0) for i in range(8)] + [(5, 1, 0), (12, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return spark.read.parquet(f"{folder}/documents.parquet")


def test_stages_on_rows_of_all_kinds(spark, tmp_path):
    """Nulls, empty and long texts, ties, repeated rows, different texts under one identifier, clashing columns."""
    rows = rows_of_all_kinds()
    docs = write(spark, tmp_path, rows)
    assert corpus_pipeline.filter_quality(spark, docs, str(tmp_path)).columns == docs.columns
    lines = corpus_pipeline.drop_lines(spark, docs, str(tmp_path))
    got = lines.collect()
    assert lines.columns == docs.columns and all(tuple(r)[5:] == ("x", 1, "g", "i", 3, 4, "c") for r in got)
    assert sum("a line that many" in (r["text"] or "") for r in got) == 1
    # of each family of like lines, under whatever identifiers, one is left and the emptied documents go; empty ones stay
    assert all(sum((r["text"] or "").startswith(rows[k][1][:60]) for r in got) == 1 for k in (0, 1)) and sum(r["doc_id"] in (5, 6, 7, 8) for r in got) == 2
    assert {9, 10, 11} <= {r["doc_id"] for r in got} and sum(r["doc_id"] is None for r in got) == 3
    near = corpus_pipeline.drop_near_duplicates(spark, docs, str(tmp_path))
    kept = Counter(r["doc_id"] for r in near.collect())
    assert near.columns == docs.columns and kept[13] == 1 and kept[9] == kept[10] == kept[11] == 1 and kept[None] == 3
    # of two families of three and two, whose members have two texts under one identifier, one document each
    families = [{r["doc_id"] for r in near.collect() if (r["text"] or "").startswith(rows[k][1][:60])} for k in (0, 1)]
    assert all(len(f) == 1 for f in families) and sum(kept[i] for i in (5, 6, 7, 8)) == 2
    mixed = corpus_pipeline.mix_sources(spark, docs, str(tmp_path))
    assert mixed.columns == docs.columns and mixed.count() > 0
    check_packing(corpus_pipeline.pack_documents(spark, docs.filter("doc_id is not null"), str(tmp_path)).collect(), [(r[0], r[1]) for r in rows if r[0] is not None])


def test_stages_on_an_empty_table(spark, tmp_path):
    docs = write(spark, tmp_path, [])
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, str(tmp_path))
        assert out.columns == docs.columns and out.count() == 0
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
