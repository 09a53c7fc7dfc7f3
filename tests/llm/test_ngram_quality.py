import math
from collections import Counter, defaultdict

import numpy as np
import pytest

from predtopics.llm import ngram_quality as nq


def brute(trusted, texts, order):
    """Plain interpolated modified Kneser-Ney; perplexity of each text."""
    raw = Counter()
    for t in trusted:
        x = b"\0" * (order - 1) + t.encode()
        raw.update(x[i : i + order] for i in range(len(x) - order + 1))
    counts = {order: raw}
    for k in range(order - 1, 0, -1):
        counts[k] = Counter(g[1:] for g in counts[k + 1])
    spare = {}
    for k, c in counts.items():
        n = Counter(c.values())
        d = nq.discounts(n[1], n[2], n[3], n[4])
        total, cut = defaultdict(int), defaultdict(float)
        for g, v in c.items():
            total[g[:-1]] += v
            cut[g[:-1]] += d[min(v, 3) - 1]
        spare[k] = d, total, cut

    def p(g):
        if not g:
            return 1 / 256
        d, total, cut = spare[len(g)]
        h, below = g[:-1], p(g[1:])
        if h not in total:
            return below
        v = counts[len(g)].get(g, 0)
        return (v - d[min(v, 3) - 1] if v else 0) / total[h] + cut[h] / total[h] * below

    out = []
    for t in texts:
        x = b"\0" * (order - 1) + (t or "").encode()
        logs = [math.log(p(x[i : i + order])) for i in range(len(x) - order + 1)]
        out.append(math.exp(-sum(logs) / len(logs)) if logs else None)
    return out


@pytest.mark.parametrize("most", [nq.MOST, 100])
def test_against_a_plain_model(spark, sf_dir, most, monkeypatch):
    monkeypatch.setattr(nq, "CHUNK", 3000)
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").where("doc_id < 40").collect()]
    rows += [(900, "é" * 50 + "zq" * 40), (901, ""), (902, None)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    trusted = [t for i, t in rows if i < 25]
    model = nq.train(frame.where("doc_id < 25"))
    got = {r.doc_id: r.perplexity for r in nq.perplexity(frame, model, most=most).collect()}
    for (i, _), want in zip(rows, brute(trusted, [t for _, t in rows], nq.ORDER)):
        assert (got[i] is None) if want is None else got[i] == pytest.approx(want, rel=1e-4)


def test_probabilities_sum_to_one(spark):
    frame = spark.createDataFrame([("abracadabra " * 5,), ("the cat sat on the mat",)], "text string")
    model = nq.train(frame, order=3)
    wanted = spark.createDataFrame([(ord("r") << 16 | ord("a") << 8 | w,) for w in range(256)], "gram long")
    assert sum(math.exp(r.logp) for r in nq.log_probs(model, wanted).collect()) == pytest.approx(1, abs=1e-5)


def test_whole_table_keeps_ordinary_text(spark, sf_dir):
    got = nq.op2_quality(spark, sf_dir).toPandas()
    assert got["doc_id"].nunique() == len(got) == spark.read.parquet(f"{sf_dir}/documents.parquet").count()
    assert got["keep"].mean() > 0.95
    assert (got["keep"] == (got["perplexity"] <= got["threshold"])).all()


def test_edges(spark):
    rows = [(1, "en", "some words here"), (1, "en", "some words here"), (2, None, None), (None, "xx", "other words"), (3, "de", "")]
    frame = spark.createDataFrame(rows, "doc_id long, lang string, text string").selectExpr("*", "'clash' as keep", "1 as block", "2 as gram")
    ids = spark.createDataFrame([(1,), (1,), (None,)], "doc_id long")
    got = nq.classify(frame, ids).collect()
    assert sorted((r.doc_id or 0, r.keep) for r in got) == [(0, False), (1, True), (1, True), (2, False), (3, False)]
    assert all(r.keep for r in nq.classify(frame, ids.limit(0)).collect() if r.n_bytes)
    assert nq.classify(frame.limit(0), ids).count() == 0
    assert np.array(nq.grams(b"")).size == 0


def test_thresholds_are_the_plain_quantile_of_all_trusted_texts_unseen(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").where("doc_id < 60").select("doc_id", "lang", "text")
    ids = docs.where("doc_id % 3 > 0").select("doc_id")
    got = {r.doc_id: r for r in nq.classify(docs, ids, quantile=0.8).collect()}
    fold = {r.doc_id: r.f for r in docs.selectExpr("doc_id", f"pmod(xxhash64(cast(doc_id as string)), {nq.HELD}) as f").collect()}
    text = {r.doc_id: r.text for r in docs.collect()}
    for k in range(nq.HELD):
        trained = [t for i, t in text.items() if i % 3 and fold[i] != k]
        judged = [i for i in text if (fold[i] == k if i % 3 else k == 0)]
        for i, want in zip(judged, brute(trained, [text[i] for i in judged], nq.ORDER)):
            assert got[i].perplexity is None if want is None else got[i].perplexity == pytest.approx(want, rel=1e-4)
    for lang in {r.lang for r in got.values()}:
        own = sorted(r.perplexity for r in got.values() if r.lang == lang and r.trusted and r.perplexity is not None)
        assert own and {r.threshold for r in got.values() if r.lang == lang} == {own[math.ceil(0.8 * len(own)) - 1]}


def test_labelled_good_text_stays_and_labelled_bad_text_goes(spark):
    sf_dir = "/root/testdata/sf0.01"
    got = nq.op2_quality(spark, sf_dir).toPandas().merge(spark.read.parquet(f"{sf_dir}/labels.parquet").toPandas(), on="doc_id")
    calm = got[got["toxic"] == 0]
    assert calm[calm["quality"] == 1]["keep"].mean() > 0.99
    assert calm[calm["quality"] == 0]["keep"].mean() < 0.1


def test_all_trusted_text_in_one_fold_trains_on_itself(spark):
    frame = spark.createDataFrame([(1, "en", "some words here"), (2, "en", "zzqqxx")], "doc_id long, lang string, text string")
    got = {r.doc_id: r for r in nq.classify(frame, frame.where("doc_id = 1").select("doc_id")).collect()}
    for i, want in zip((1, 2), brute(["some words here"], ["some words here", "zzqqxx"], nq.ORDER)):
        assert got[i].perplexity == pytest.approx(want, rel=1e-4)
    assert got[1].keep and not got[2].keep and got[1].threshold == got[2].threshold == got[1].perplexity
