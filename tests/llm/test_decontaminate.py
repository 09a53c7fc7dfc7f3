import re

import pytest

from predtopics.llm import decontaminate as dc


def words(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", low)


def brute(text, items):
    w, hit, named = words(text), set(), set()
    for item, t in items:
        x = words(t)
        if item is None or not x:
            continue
        size = min(10, len(x))
        wins = {tuple(x[i : i + size]) for i in range(len(x) - size + 1)}
        for i in range(len(w) - size + 1):
            if tuple(w[i : i + size]) in wins:
                hit |= set(range(i, i + size))
                named.add(str(item))
    return len(w), len(hit), len(named), sorted(named)


@pytest.mark.parametrize("most", [200_000, 3])
def test_whole_table(spark, sf_dir, most):
    docs, items = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    got = {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.item_ids) for r in dc.decontaminate(docs, items, most=most).collect()}
    pairs = [(r.item_id, r.text) for r in items.collect()]
    assert got == {r.doc_id: brute(r.text, pairs) for r in docs.collect()}
    assert any(v[1] for v in got.values())


def test_hard_cases(spark):
    long = " ".join(f"w{i}" for i in range(25))
    items = [(1, "One two"), (2, long), (3, long), (None, "zz"), (4, None), (5, "..."), (6, "a a a a a a a a a a a"), (7, "ÉÀ ß"), (10, "x")]
    texts = [None, "", "one, TWO! one-two", long.upper(), "w0 " + long + " w24", " ".join(f"w{i}" for i in range(5, 14)), "a " * 30, "éà ß ÉÀ ß", "x" + " y" * 5000 + " X", "zz", "one two"]
    rows = [(i, t, "clash") for i, t in enumerate(texts)] + [(2, texts[2], "again"), (None, "one two", "")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, n_words string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    for most in (200_000, 2):
        got = sorted((r.doc_id if r.doc_id is not None else -1, r.n_words, r.n_hit, r.n_items, tuple(r.item_ids)) for r in dc.decontaminate(frame, bench, most=most).collect())
        want = sorted((i if i is not None else -1, *brute(t, items)[:3], tuple(brute(t, items)[3])) for i, t, _ in rows)
        assert got == want
    assert dc.decontaminate(frame.limit(0), bench).count() == 0
    assert {r.n_hit for r in dc.decontaminate(frame, bench.limit(0)).collect()} == {0}


def test_nothing_but_expressions(spark, sf_dir):
    docs, items = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    plan = dc.decontaminate(docs, items)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)
