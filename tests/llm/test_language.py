import zlib

import numpy as np

from predtopics.llm import language


def test_gradients_are_those_of_the_loss():
    rng = np.random.default_rng(0)
    net = language.ByteNet.fresh(["a", "b", "c"], rng)
    x, y = rng.integers(0, 256, (5, 40)).astype(np.uint8), np.array([0, 1, 2, 1, 0])
    for p in net.parameters():
        p[...] = p.astype(np.float64)
    loss = lambda: -net.log_probs(x)[np.arange(5), y].mean()
    for p, g in zip(net.parameters(), net.gradients(x, y)):
        for at in zip(*(rng.integers(0, s, 6) for s in p.shape)):
            old, step = p[at], 1e-2
            p[at] = old + step
            up = loss()
            p[at] = old - step
            down = loss()
            p[at] = old
            assert abs((up - down) / (2 * step) - g[at]) < 2e-2


def test_held_out_accuracy(spark):
    got = language.op5_language(spark, "/root/testdata/sf0.01").collect()
    truth = {r.doc_id: (r.lang, r.text) for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()}
    assert {r.doc_id for r in got} == set(truth)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in got)
    held = [r for r in got if r.held_out]
    assert np.mean([r.lang_pred == truth[r.doc_id][0] for r in held]) > 0.97
    assert all(0 <= r.score <= 1 for r in got)


def test_edges(spark):
    texts = [("the of and " * 30, "en"), ("der die und " * 30, "de")] * 20
    net = language.fit([t for t, _ in texts], [x for _, x in texts])
    frame = spark.createDataFrame([(1, None), (1, None), (2, ""), (None, "123 ... 456"), (3, "der und die"), (4, "the and of " * 20_000)], "doc_id long, text string").selectExpr("*", "'x' as lang_pred", "1 as score")
    got = sorted(((r.doc_id or 0, r.lang_pred, r.score > 0) for r in language.identify(frame, net).collect()))
    assert got == [(0, "und", False), (1, "und", False), (1, "und", False), (2, "und", False), (3, "de", True), (4, "en", True)]
    assert language.identify(frame.limit(0), net).count() == 0
    assert language.train(frame.selectExpr("doc_id", "text", "cast(null as string) as lang")).langs == ["und"]


def test_prediction_is_the_mean_of_windows_by_their_bytes():
    rng = np.random.default_rng(2)
    net = language.ByteNet.fresh(["a", "b", "c"], rng)
    for text in ("one two", "é" * 300 + " words", "x" * 256, "long text " * 90):
        data, total = text.encode(), np.zeros(3)
        for at in range(0, len(data), language.WINDOW):
            piece = data[at : at + language.WINDOW]
            vec = net.vectors[list(piece.ljust(language.WINDOW, b"\0"))].astype(np.float64)
            pooled = []
            for w in language.WIDTHS:
                seen = np.array([vec[i : i + w].ravel() @ net.filters[w].astype(np.float64) for i in range(language.WINDOW - w + 1)])
                pooled.append(np.maximum(seen.max(axis=0) + net.bias[w], 0))
            logits = np.concatenate(pooled) @ net.out + net.out_bias
            p = np.exp(logits - logits.max())
            total += p / p.sum() * len(piece)
        (lang,), (score,) = language.predict(net, [text])
        assert net.langs.index(lang) == total.argmax() and abs(score - total.max() / len(data)) < 1e-4


def test_training_sees_the_whole_of_a_long_text(spark):
    text = "".join(f"{i:05d}" for i in range(20_000))
    got = spark.createDataFrame([(text,), ("short",), ("",)], "text string").select(language.spread_out(language.F.col("text")).alias("t")).collect()
    parts = got[0].t.split(" ")
    assert len(parts) == language.TRAIN_WINDOWS and parts[0] == text[: language.STRETCH] and parts[-1] == text[-language.STRETCH :] and all(p in text for p in parts)
    assert [r.t for r in got[1:]] == ["short", ""]
