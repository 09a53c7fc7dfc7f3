import tracemalloc

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from predtopics.llm import bpe, common, language, simhash


def batch(texts):
    return pa.RecordBatch.from_arrays([pa.array(range(len(texts)), pa.int64()), pa.array(texts, pa.string())], names=["doc_id", "text"])


def whole(run, keeps=None):
    return list(common.lean(run, keeps)(iter([batch(["one two three", None, "naïve 12"])])))


def test_a_worker_keeps_only_what_its_own_operator_uses_again():
    bpe.tokenizer.cache_clear()
    encode = bpe._encoder(bpe.default_vocabulary(), ["doc_id", "ids"], False)
    first = whole(encode, bpe.tokenizer)
    assert whole(encode, bpe.tokenizer) == first and bpe.tokenizer.cache_info().misses == 1
    whole(simhash._fingerprints)
    assert bpe.tokenizer.cache_info().currsize == 0
    assert whole(encode, bpe.tokenizer) == first


def test_operators_run_as_lean_tasks(spark, monkeypatch):
    seen = []
    for module in (bpe, language, simhash):
        monkeypatch.setattr(module, "lean", lambda run, keeps=None: seen.append(keeps) or common.lean(run, keeps))
    docs = spark.createDataFrame([(1, "one two three")], "doc_id long, text string")
    net = language.ByteNet.fresh(["en"], np.random.default_rng(1))
    frames = [bpe.encode(docs), language.identify(docs, net), simhash.fingerprints(docs)]
    assert seen == [bpe.tokenizer, None, None] and all(f.count() == 1 for f in frames)


def test_windows_of_a_slice_take_little_memory_at_once():
    net = language.ByteNet.fresh(["a", "b"], np.random.default_rng(1))
    texts = ["some words of a text " * 200] * 64
    whole_at_once = language.predict(net, texts, most=1 << 20)
    tracemalloc.start()
    got = language.predict(net, texts)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 16 << 20
    assert got[0] == whole_at_once[0] and np.allclose(got[1], whole_at_once[1])


def test_a_kept_text_goes_to_workers_once(spark):
    net = language.ByteNet.fresh(["a", "b"], np.random.default_rng(1))
    docs = spark.createDataFrame([(1, "one two three"), (2, None), (None, "123"), (3, "quatre")], "doc_id long, text string")
    both = language.identify(docs, net, ("doc_id", "text"))
    assert "__text" not in both._jdf.queryExecution().analyzed().toString()
    apart = language.identify(docs.withColumn("other", F.col("text")), net, ("doc_id", "other"))
    assert sorted(map(str, map(tuple, both.collect()))) == sorted(map(str, map(tuple, apart.collect())))
    assert both.columns == ["doc_id", "text", "lang_pred", "score"]
