import numpy as np
import xxhash

from predtopics.llm import simhash


def plain_fingerprint(text):
    import re

    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall("[^\x20\x09-\x0d]+", low)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(prints):
    """{key: smallest key reachable} over all pairs."""
    keys = sorted(prints)
    root = {k: k for k in keys}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i, a in enumerate(keys):
        for b in keys[i + 1 :]:
            if (prints[a] ^ prints[b]).bit_count() <= 4:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {k: find(k) for k in keys}


def test_fingerprints_match_a_plain_rendering():
    for text in (None, "", " \t\n", "One", "a b c d", "A b C d e", "É é x y z w " * 50, "la\xa0le \x85 q w e r t y", "x" * 50_000 + " " + "y z " * 9000):
        assert simhash.fingerprint((text or "").encode()) == plain_fingerprint(text)


def test_whole_table_against_all_pairs(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = {r.doc_id: (r.fp & (2**64 - 1), r.component_id) for r in simhash.near_duplicates(docs).collect()}
    want = {r.doc_id: plain_fingerprint(r.text) for r in docs.select("doc_id", "text").collect()}
    assert {k: v[0] for k, v in got.items()} == want
    assert {k: v[1] for k, v in got.items()} == brute_components(want)


def test_links_at_every_distance_and_across_blocks(spark, monkeypatch):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 2**63, 6, dtype=np.uint64)
    made = {int(x) for x in base}
    for b in base.tolist():
        for bits in range(1, 9):
            for _ in range(12):
                made.add(b ^ sum(1 << int(i) for i in rng.choice(64, bits, replace=False)))
    prints = dict(enumerate(sorted(made)))
    frame = spark.createDataFrame([(v - 2**64 if v >= 2**63 else v,) for v in prints.values()], "fp long")
    from predtopics.llm.common import components

    want = brute_components(prints)
    want = {prints[k]: prints[v] for k, v in want.items()}
    roots = {r.node & (2**64 - 1): r.root & (2**64 - 1) for r in components(simhash.links(frame)).collect()}
    classes = lambda m: {frozenset(k for k in m if m[k] == v) for v in m.values()}
    assert classes({k: roots.get(k, k) for k in want}) == classes(want)


def test_buckets_beyond_a_block_are_dealt_out(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(simhash, "BLOCK", 8)
    rng = np.random.default_rng(1)
    keys = np.sort(np.concatenate([np.full(n, k) for k, n in enumerate([1, 3, 40, 8, 9, 2, 17, 1])])).astype(np.int64)
    prints = rng.integers(0, 2**40, len(keys)).astype(np.int64)
    for step in (1, 5, 7, 100):
        batches = [pa.RecordBatch.from_arrays([pa.array(keys[i : i + step]), pa.array(prints[i : i + step])], names=["key", "fp"]) for i in range(0, len(keys), step)]
        out = [r for b in simhash._scan(iter(batches)) for r in zip(*(c.to_pylist() for c in b.columns))]
        dealt = [r for r in out if r[0] == 1]
        long = {k for k, n in enumerate([1, 3, 40, 8, 9, 2, 17, 1]) if n > 8}
        assert sorted((r[1], r[2]) for r in dealt) == sorted((int(k), int(p)) for k, p in zip(keys, prints) if k in long)
        sizes = {}
        for r in dealt:
            sizes[r[1], r[3]] = sizes.get((r[1], r[3]), 0) + 1
        assert max(sizes.values()) <= 8


def test_edges(spark):
    from pyspark.sql import functions as F

    rows = [(3, None), (1, ""), (2, "a b c d e f"), (2, "a b c d e f"), (None, "a b c d e f")]
    frame = spark.createDataFrame(rows, "doc_id long, text string").withColumn("fp", F.lit("clash")).withColumn("component_id", F.lit(0))
    got = sorted(((r.doc_id is None, r.doc_id or 0, r.component_id) for r in simhash.near_duplicates(frame).collect()))
    assert got == [(False, 1, 1), (False, 2, 2), (False, 2, 2), (False, 3, 1), (True, 0, 2)]
    assert simhash.near_duplicates(frame.limit(0)).count() == 0
