"""SimHash near-duplicate classes by multi-index hashing.

A fingerprint has 64 bits in two segments of 32. Two fingerprints at 4 or fewer differing bits
differ by at most 2 bits in the high segment or by at most 1 bit in the low one, so these are looked
up in one table per segment. For the high segment both sides enumerate the ball of radius 1 and meet in
the middle; for the low one the ball of radius 1 meets the plain segments. Each match is verified on the
complete distance. Segments of 32 bits keep tables sparse up to billions of fingerprints.

Fingerprints are made distinct first, so exact copies cost one entry. A table bucket is compared in
blocks of ``BLOCK`` members, and buckets beyond a block are dealt out as pairs of blocks to many tasks;
within a block only a spanning star of each linked class leaves the task, never all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checkpoint, components, join_unique, lean, table

#: Members of a bucket that one task compares with each other.
BLOCK = 2048
WORDS, SEED, RADIUS = 4, 42, 4


def fingerprint(data: bytes, words: int = WORDS, seed: int = SEED) -> int:
    """Unsigned 64-bit fingerprint of one text in UTF-8; no words: 0; fewer than ``words``: the whole sequence is one shingle."""
    tokens = data.lower().split()  # bytes: A-Z only, and white space is 0x20 and 0x09-0x0D
    n = len(tokens)
    if not n:
        return 0
    flat = b" ".join(tokens)
    if n <= words:
        hashes = np.array([xxhash.xxh64_intdigest(flat, seed)], dtype=np.uint64)
    else:
        size = np.fromiter(map(len, tokens), dtype=np.int64, count=n)
        end = np.cumsum(size + 1) - 1
        start = end - size
        digest = xxhash.xxh64_intdigest
        hashes = np.fromiter((digest(flat[a:b], seed) for a, b in zip(start[: n - words + 1].tolist(), end[words - 1 :].tolist())), dtype=np.uint64, count=n - words + 1)
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 16384):
        part = hashes[at : at + 16384].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    bits = (2 * ones > len(hashes)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = batch.column(1).cast(pa.large_binary())
        prints = np.fromiter((fingerprint(x.as_py() or b"") for x in texts), dtype=np.uint64, count=len(texts))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints.view(np.int64))], names=["doc_id", "fp"])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp) with fp the fingerprint's bits as a signed long."""
    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(lean(_fingerprints), f"doc_id {kind}, fp long")


def _entries(prints: DataFrame) -> DataFrame:
    """Table entries (key, fp): a fingerprint's own value and 32 neighbours in either segment."""
    high = F.shiftrightunsigned("fp", 32)
    low = F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF))
    flips = F.array(F.lit(0).cast("long"), *[F.lit(1 << i).cast("long") for i in range(32)])
    one = lambda seg, table: F.transform(flips, lambda m: seg.bitwiseXOR(m).bitwiseOR(F.lit(table << 32).cast("long")))
    return prints.select(F.explode(F.concat(one(high, 1), one(low, 0))).alias("key"), "fp")


def _distance_ok(a: np.ndarray, b: np.ndarray, radius: int) -> np.ndarray:
    return np.bitwise_count(a ^ b) <= radius


def stars(left: np.ndarray, right: np.ndarray | None, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """Spanning stars of the classes that links within ``left`` (and between it and ``right``) make."""
    both = left if right is None else np.concatenate([left, right])
    n, seen, out_a, out_b = len(both), np.zeros(len(both), dtype=bool), [], []
    for i in range(n):
        if seen[i]:
            continue
        seen[i] = True
        group, front = [], np.array([i])
        while len(front):
            near = np.zeros(n, dtype=bool)
            for at in range(0, len(front), 256):
                near |= _distance_ok(both[front[at : at + 256], None], both[None, :], radius).any(axis=0)
            front = np.flatnonzero(near & ~seen)
            seen[front] = True
            group.append(front)
        members = np.concatenate(group)
        if len(members):
            out_a.append(both[members])
            out_b.append(np.full(len(members), both[i]))
    empty = np.zeros(0, dtype=np.uint64)
    return (np.concatenate(out_a), np.concatenate(out_b)) if out_a else (empty, empty)


def _rows(kind: int, a: np.ndarray, b: np.ndarray, block: int = 0) -> pa.RecordBatch:
    n = len(a)
    return pa.RecordBatch.from_arrays(
        [pa.array(np.full(n, kind, np.int32)), pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), pa.array(np.full(n, block, np.int32))], names=["kind", "a", "b", "block"]
    )


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Entries sorted by key -> links (kind 0), and members of buckets that exceed a block (kind 1: key, fp, block)."""

    def settle(keys: np.ndarray, prints: np.ndarray) -> Iterator[pa.RecordBatch]:
        """Whole buckets, each of at most BLOCK members."""
        cut = np.flatnonzero(np.diff(keys)) + 1
        start = np.concatenate([[0], cut])
        size = np.diff(np.concatenate([start, [len(keys)]]))
        a, b = [], []
        wide = size > 24
        for s, n in zip(start[wide].tolist(), size[wide].tolist()):
            x, y = stars(np.unique(prints[s : s + n]), None)
            a.append(x)
            b.append(y)
        few = np.repeat(~wide, size)
        k, p = keys[few], prints[few]
        for d in range(1, 24):
            i = np.flatnonzero(k[d:] == k[:-d]) if len(k) > d else []
            if not len(i):
                break
            ok = i[_distance_ok(p[i], p[i + d], RADIUS) & (p[i] != p[i + d])]
            a.append(p[ok])
            b.append(p[ok + d])
        if a:
            links = np.unique(np.stack([np.minimum(x := np.concatenate(a), y := np.concatenate(b)), np.maximum(x, y)]), axis=1)
            if links.shape[1]:
                yield _rows(0, links[0].copy(), links[1].copy())

    held_k, held_p, sent = np.zeros(0, np.uint64), np.zeros(0, np.uint64), 0
    for batch in batches:
        keys = np.concatenate([held_k, batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)])
        prints = np.concatenate([held_p, batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)])
        if not len(keys):
            continue
        if sent and (first := int(np.searchsorted(keys, keys[0], side="right"))) < len(keys):  # the long bucket ends here
            yield _rows(1, keys[:first], prints[:first], sent)
            keys, prints, sent = keys[first:], prints[first:], 0
        if not sent:
            cut = np.flatnonzero(np.diff(keys)) + 1
            start = np.concatenate([[0], cut])
            size = np.diff(np.concatenate([start, [len(keys)]]))
            long = size[:-1] > BLOCK
            for s, n in zip(start[:-1][long].tolist(), size[:-1][long].tolist()):
                for j, at in enumerate(range(s, s + n, BLOCK)):
                    yield _rows(1, keys[at : min(s + n, at + BLOCK)], prints[at : min(s + n, at + BLOCK)], j)
            keep = np.repeat(~long, size[:-1])
            last = int(start[-1])
            if keep.any():
                yield from settle(keys[:last][keep], prints[:last][keep])
            keys, prints = keys[last:], prints[last:]
        while len(keys) > 2 * BLOCK or (sent and len(keys) > BLOCK):
            yield _rows(1, keys[:BLOCK], prints[:BLOCK], sent)
            keys, prints, sent = keys[BLOCK:], prints[BLOCK:], sent + 1
        held_k, held_p = keys, prints
    if sent:
        yield _rows(1, held_k, held_p, sent)
    elif len(held_k) > BLOCK:
        for j, at in enumerate(range(0, len(held_k), BLOCK)):
            yield _rows(1, held_k[at : at + BLOCK], held_p[at : at + BLOCK], j)
    elif len(held_k):
        yield from settle(held_k, held_p)


def _pair(key, pdf):  # noqa: ANN001
    """Two blocks of one bucket (or one with itself)."""
    import pandas as pd

    a, b = stars(np.unique(pdf["fp"].to_numpy().view(np.uint64)), None)
    return pd.DataFrame({"a": a.view(np.int64), "b": b.view(np.int64)})


def links(prints: DataFrame) -> DataFrame:
    """Distinct fingerprints (fp) -> links (a, b) whose classes are those of all links at RADIUS or fewer bits."""
    found = checkpoint(_entries(prints).repartition("key").sortWithinPartitions("key").mapInArrow(lean(_scan), "kind int, a long, b long, block int"))
    out = found.where("kind = 0").select("a", "b")
    long = found.where("kind = 1").select(F.col("a").alias("key"), F.col("b").alias("fp"), "block")
    if not long.isEmpty():
        blocks = long.groupBy("key").agg((F.max("block") + 1).alias("blocks"))
        dealt = long.join(blocks, "key").select("key", "fp", "block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
        pairs = dealt.select("key", F.least("block", "other").alias("p"), F.greatest("block", "other").alias("q"), "fp")
        out = out.unionAll(pairs.groupBy("key", "p", "q").applyInPandas(_pair, "a long, b long"))
    return out


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: (doc_id, fp, component_id), the smallest id of the document's class.

    Null and empty texts have fingerprint 0 and form one class with whatever is within RADIUS of it;
    repeated rows stay repeated; a null id is kept and never names a class that has another id.
    An empty frame gives an empty one. Other columns are ignored.
    """
    prints = checkpoint(fingerprints(docs, id_col, text_col))
    distinct = checkpoint(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = checkpoint(components(links(distinct)).select(F.col("node").alias("fp"), "root"))
    linked = checkpoint(join_unique(distinct, roots, ["fp"], "left"))  # root is null for a fingerprint without links
    ids = checkpoint(linked.where("root is not null").groupBy("root").agg(F.min("least").alias("of_class")))
    named = join_unique(linked, ids, ["root"], "left").select("fp", F.when(F.col("root").isNull(), F.col("least")).otherwise(F.col("of_class")).alias("component_id"))
    return join_unique(prints, checkpoint(named), ["fp"]).select("doc_id", "fp", "component_id")


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
