"""Exact dedup with Patricia-trie owners.

Texts travel to the task that owns their (length, content hash); there their
full bytes enter a compressed radix trie whose terminal nodes hold the owner
identifier and the number of copies. Each map task first folds its own copies
in the same kind of trie, so a text sends one row per map task, however many
copies it has. Owners of groups of two or more come back to the documents on
the hash; texts never do.
"""

from __future__ import annotations

import pickle
import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blobs, free, map_batches, text_of

BUDGET = 48 << 20


def _shared(a: bytes, b: bytes, start: int) -> int:
    """Length of the common prefix of a and b[start:]."""
    lo, hi = 0, min(len(a), len(b) - start)
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if a[lo:mid] == b[start + lo : start + mid]:
            lo = mid
        else:
            hi = mid - 1
    return lo


class RadixTrie:
    """Compressed radix trie over bytes; a node is [label, children, payload].

    A payload is [owner, copies, tag]. ``keep`` chooses the owner among
    equals; a null identifier owns only where there is no other.
    """

    def __init__(self, keep=min):
        self.root, self.keep, self.bytes = [b"", {}, None], keep, 0

    def _merge(self, node, owner, copies, tag):
        if node[2] is None:
            node[2] = [owner, copies, tag]
            self.bytes += 120
            return
        have = node[2]
        have[1] += copies
        have[0] = owner if have[0] is None else have[0] if owner is None else self.keep(have[0], owner)

    def insert(self, key: bytes, owner, copies: int, tag) -> None:
        node, i = self.root, 0
        while i < len(key):
            child = node[1].get(key[i])
            if child is None:
                node[1][key[i]] = leaf = [key[i:], {}, None]
                self.bytes += len(key) - i + 300
                return self._merge(leaf, owner, copies, tag)
            label = child[0]
            if not key.startswith(label, i):
                m = _shared(label, key, i)
                upper = [label[:m], {label[m]: child}, None]
                child[0] = label[m:]
                node[1][key[i]] = child = upper
                self.bytes += 300
            i += len(child[0])
            node = child
        self._merge(node, owner, copies, tag)

    def items(self, node=None, prefix: bytes = b"") -> Iterator[tuple[bytes, list]]:
        """All (key, payload), without recursion."""
        stack = [(node or self.root, prefix)]
        while stack:
            n, at = stack.pop()
            at += n[0]
            if n[2] is not None:
                yield at, n[2]
            stack.extend((c, at) for c in n[1].values())

    def stem(self) -> int:
        """Length of the prefix that all keys share."""
        node, n = self.root, 0
        while len(node[1]) == 1 and node[2] is None:
            node = next(iter(node[1].values()))
            n += len(node[0])
        return n


def owners(rows, keep, budget: int = BUDGET):
    """Merge (key, owner, copies, tag) rows; yields (key, [owner, copies, tag]).

    Past the budget the subtrees below the common stem go to task-owned
    spill files (deleted with the task, read by no other), and later keys of a
    spilled subtree follow; each subtree is then merged by itself.
    """
    trie, files, stem = RadixTrie(keep), {}, 0

    def spill(key, payload):
        b = key[: stem + 1]
        if b not in files:
            files[b] = tempfile.TemporaryFile()
        pickle.dump((key, *payload), files[b])

    for key, owner, copies, tag in rows:
        if files and key[: stem + 1] in files:
            spill(key, (owner, copies, tag))
            continue
        trie.insert(key, owner, copies, tag)
        if trie.bytes > budget:
            if not files:
                stem = trie.stem()
            sizes: dict[bytes, int] = {}
            for key, _ in trie.items():
                sizes[key[: stem + 1]] = sizes.get(key[: stem + 1], 0) + len(key)
            if len(sizes) == 1 and len(next(iter(sizes))) <= stem:
                continue  # one text only
            gone = set(sorted(sizes, key=sizes.get)[-max(1, len(sizes) // 2) :])
            rest = RadixTrie(keep)
            for key, payload in trie.items():
                if key[: stem + 1] in gone:
                    spill(key, payload)
                else:
                    rest.insert(key, *payload)
            trie = rest
    yield from trie.items()
    del trie
    for f in files.values():
        f.seek(0)

        def again(f=f):
            while True:
                try:
                    yield pickle.load(f)
                except EOFError:
                    return

        yield from owners(again(), keep, budget)
        f.close()


def _rows(batches):
    for b in batches:
        yield from zip(blobs(b.column("text")), b.column("owner").to_pylist(), b.column("copies").to_pylist(), b.column("sha").to_pylist())


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", budget: int = BUDGET) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    Equal means byte-equal, null counting as the empty text. ``keep`` is
    ``min`` or ``max``. Repeated rows count as copies; rows that repeat the
    owner's identifier are all marked kept. A null identifier owns its group
    only if the group has no other. Empty input gives an empty result; extra
    columns are ignored.
    """
    choose = {"min": min, "max": max}[keep]
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"))
    keyed = base.select("doc_id", F.sha2("text", 256).alias("sha"), F.octet_length("text").alias("n_bytes"))

    def fold_copies(batches):
        seen, size = [], 0

        def out(rows):
            for at in range(0, len(rows), 1000):
                part = rows[at : at + 1000]
                yield pa.record_batch([pa.array([len(k) for k, _ in part], pa.int32()), pa.array([p[2] for _, p in part]), pa.array([k for k, _ in part], pa.binary()), pa.array([p[0] for _, p in part], pa.int64()), pa.array([p[1] for _, p in part], pa.int64())], ["n_bytes", "sha", "text", "owner", "copies"])

        trie = RadixTrie(choose)
        for row in _rows(batches):
            trie.insert(*row)
            if trie.bytes > budget:
                yield from out(list(trie.items()))
                trie = RadixTrie(choose)
        yield from out(list(trie.items()))

    def merge(batches):
        part = []
        for _, (owner, copies, sha) in owners(_rows(batches), choose, budget):
            if copies > 1:
                part.append((sha, owner, copies))
            if len(part) >= 5000:
                yield pa.record_batch(list(map(pa.array, zip(*part))), ["sha", "keep_id", "group_size"])
                part = []
        if part:
            yield pa.record_batch([pa.array([r[0] for r in part]), pa.array([r[1] for r in part], pa.int64()), pa.array([r[2] for r in part], pa.int64())], ["sha", "keep_id", "group_size"])

    sent = base.select(F.col("text").cast("binary").alias("text"), F.col("doc_id").alias("owner"), F.lit(1).cast("long").alias("copies"), F.sha2("text", 256).alias("sha"))
    folded = map_batches(sent, fold_copies, "n_bytes int, sha string, text binary, owner long, copies long")
    dealt = folded.repartition("n_bytes", "sha")
    groups = map_batches(dealt, merge, "sha string, keep_id long, group_size long")
    return keyed.join(groups, "sha", "left").select(
        "doc_id",
        F.coalesce("keep_id", "doc_id").alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        F.col("doc_id").eqNullSafe(F.coalesce("keep_id", "doc_id")).alias("kept"),
        F.col("sha").alias("text_sha256"),
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """The documents that stay, all columns, one row per group of equal texts, whatever identifiers they share."""
    sha, owner = free(docs, "__sha"), free(docs, "__owner")
    stay = exact_groups(docs, id_col, text_col, keep).filter("kept").select(F.col("text_sha256").alias(sha), F.col("doc_id").alias(owner)).distinct()
    own = (F.sha2(text_of(text_col), 256) == F.col(sha)) & F.col(id_col).cast("long").eqNullSafe(F.col(owner))
    return docs.join(stay, own).dropDuplicates([sha]).drop(sha, owner)


ORACLE = """
SELECT doc_id, max(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)
"""
