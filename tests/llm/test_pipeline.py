import sys
from pathlib import Path

from pyspark.sql import functions as F
from tokenizers import Tokenizer

sys.path.insert(0, str(Path(__file__).parent))
from test_decontaminate import brute as contamination
from test_secrets import all_spans
from test_simhash import brute_components, plain_fingerprint

import corpus_pipeline as cp
from predtopics.llm import bpe


def redact(text):
    out, at = "", 0
    for a, _, b, _ in all_spans(text):
        if a >= at:
            out += text[at:a] + "[SECRET]"
        at = max(at, b)
    return out + text[at:]


def test_stages_against_brute_force(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    rows = {r.doc_id: r.text for r in docs.collect()}
    want = {k: t for k, t in rows.items() if any(c.isalpha() for c in t)}
    prints = {k: plain_fingerprint(t) for k, t in want.items()}
    want = {k: t for k, t in want.items() if brute_components(prints)[k] == k} if len(want) < 50 else {k: want[k] for k in {*brute_components(prints).values()}}
    want = {k: redact(t) for k, t in want.items() if not contamination(t, items)[1]}
    library = Tokenizer.from_file(bpe.default_vocabulary())
    got = cp.run(spark, sf_dir).collect()
    assert {r.doc_id: r.ids for r in got} == {k: library.encode(t, add_special_tokens=False).ids for k, t in want.items()}
    assert all(r.round_trip and r.n_tokens == len(r.ids) for r in got)


def test_stages_keep_columns_and_survive_odd_rows(spark, sf_dir):
    base = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(40)
    odd = spark.createDataFrame([(None, None, None, None, None), (7000, "", "en", "s", 0), (7001, "123 456", None, "s", 7), (0, "again the same id", "en", "s", 17), (None, "the and of password=b7db7aa4a5fcc78305", None, None, None)], base.schema)
    docs = base.unionByName(odd)
    for name, stage in cp.STAGES:
        out = stage(spark, docs, sf_dir)
        if name != "bpe":
            assert out.columns == base.columns
        got = {(r.doc_id, r[1] if name != "bpe" else None) for r in out.collect()}
        if name == "language_id":
            assert not {7000, 7001} & {k for k, _ in got}
        if name == "secret_scans":
            assert (None, "the and of [SECRET]") in got and (None, None) in got or (None, "") in got
        assert stage(spark, docs.limit(0), sf_dir).count() == 0
    assert F is not None


def test_one_row_of_each_class_stays_whatever_its_id(spark):
    words = ["alpha beta gamma delta epsilon zeta eta theta", "one two three four five six seven eight nine", "red green blue black white brown pink grey", "north south east west up down left right"]
    a, b, c, d = words
    rows = [(1, a), (2, a), (2, b), (2, c), (2, c), (None, c), (None, d), (None, d), (None, d), (5, "apple " + b), (None, None), (7, "")]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = sorted(((r.doc_id, r.text) for r in cp.drop_near_duplicates(spark, docs.repartition(3), "").collect()), key=str)
    prints = dict(enumerate(plain_fingerprint(t or "") for _, t in rows))
    classes = {}
    for k, root in brute_components(prints).items():
        classes.setdefault(root, []).append(rows[k])
    want = [min(members, key=lambda r: (r[0] is None, r[0] or 0, r[1] or "")) for members in classes.values()]
    assert got == sorted(want, key=str) and (2, b) in got and got.count((None, d)) == 1
