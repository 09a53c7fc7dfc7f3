"""Language identification by a byte convolutional network, trained in numpy.

A text is cut into windows of ``WINDOW`` bytes. Bytes have learned vectors; filters of several widths run over a window, each
filter keeps its largest response (max pooling), and a softmax layer over these gives the languages. A text's
probabilities are the mean over all its windows, weighted by their bytes, so whole texts count.

Applied, a filter bank of one width is a single matrix product over the window's strided byte vectors, for many windows at once.
Training (on the driver, or wherever ``train`` is called) sees at most ``SAMPLE`` labelled rows of each language, chosen by a
hash of the id, and of each ``TRAIN_WINDOWS`` stretches spread over the whole text: bounded whatever the table's size.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, sized, table

WINDOW, WIDTHS, FILTERS, DEPTH = 256, (2, 3, 5), 24, 8
#: Labelled rows of a language that training sees, stretches of each, and characters of a stretch (as many bytes at least as a window has).
SAMPLE, TRAIN_WINDOWS, STRETCH = 600, 16, 256
EPOCHS, BATCH, RATE, SEED = 6, 64, 0.004, 7
LETTER = regex.compile(r"\p{L}")


@dataclass
class ByteNet:
    langs: list[str]
    vectors: np.ndarray
    filters: dict[int, np.ndarray] = field(default_factory=dict)
    bias: dict[int, np.ndarray] = field(default_factory=dict)
    out: np.ndarray | None = None
    out_bias: np.ndarray | None = None

    @classmethod
    def fresh(cls, langs: list[str], rng: np.random.Generator) -> ByteNet:
        net = cls(langs, rng.normal(0, 0.3, (256, DEPTH)).astype(np.float32))
        for w in WIDTHS:
            net.filters[w] = rng.normal(0, (2 / (w * DEPTH)) ** 0.5, (w * DEPTH, FILTERS)).astype(np.float32)
            net.bias[w] = np.zeros(FILTERS, np.float32)
        net.out = rng.normal(0, 0.1, (FILTERS * len(WIDTHS), len(langs))).astype(np.float32)
        net.out_bias = np.zeros(len(langs), np.float32)
        return net

    def _responses(self, windows: np.ndarray, width: int) -> np.ndarray:
        """(windows, places, filters) of one width."""
        seen = self.vectors[windows]
        n, size, depth = seen.shape
        places = size - width + 1
        strided = np.lib.stride_tricks.as_strided(seen, (n, places, width * depth), (seen.strides[0], seen.strides[1], seen.strides[2]))
        return (strided.reshape(n * places, width * depth) @ self.filters[width]).reshape(n, places, FILTERS)

    def log_probs(self, windows: np.ndarray) -> np.ndarray:
        pooled = [np.maximum(self._responses(windows, w).max(axis=1) + self.bias[w], 0) for w in WIDTHS]
        logits = np.concatenate(pooled, axis=1) @ self.out + self.out_bias
        top = logits.max(axis=1, keepdims=True)
        return logits - top - np.log(np.exp(logits - top).sum(axis=1, keepdims=True))

    def parameters(self) -> list[np.ndarray]:
        return [self.vectors, *self.filters.values(), *self.bias.values(), self.out, self.out_bias]

    def gradients(self, windows: np.ndarray, target: np.ndarray) -> list[np.ndarray]:
        n, size = windows.shape
        pooled, best = [], {}
        for w in WIDTHS:
            r = self._responses(windows, w)
            best[w] = r.argmax(axis=1)
            pooled.append(np.take_along_axis(r, best[w][:, None, :], axis=1)[:, 0, :] + self.bias[w])
        hidden = np.concatenate(pooled, axis=1)
        active = np.maximum(hidden, 0)
        logits = active @ self.out + self.out_bias
        p = np.exp(logits - logits.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        p[np.arange(n), target] -= 1
        p /= n
        back = (p @ self.out.T) * (hidden > 0)
        d_vectors, d_filters, d_bias = np.zeros_like(self.vectors), [], []
        for k, w in enumerate(WIDTHS):
            b = back[:, k * FILTERS : (k + 1) * FILTERS]  # the gradient goes to the place of the largest response
            at = best[w][:, :, None] + np.arange(w)
            taken = windows[np.arange(n)[:, None, None], at]  # (n, filters, width)
            seen = self.vectors[taken].reshape(n, FILTERS, w * DEPTH)
            d_filters.append(np.einsum("nf,nfk->kf", b, seen))
            d_bias.append(b.sum(axis=0))
            np.add.at(d_vectors, taken.reshape(-1), (b[:, :, None] * self.filters[w].T[None]).reshape(-1, DEPTH))
        return [d_vectors, *d_filters, *d_bias, active.T @ p, p.sum(axis=0)]


def windows_of(data: bytes) -> np.ndarray:
    """All of a text in rows of WINDOW bytes, zeros at the end."""
    rows = max(1, -(-len(data) // WINDOW))
    return np.frombuffer(data.ljust(rows * WINDOW, b"\0"), np.uint8).reshape(rows, WINDOW)


def fit(texts: list[str], labels: list[str], epochs: int = EPOCHS, seed: int = SEED) -> ByteNet:
    """A network for the languages of ``labels``; each text gives whole windows and short snippets of random length."""
    rng = np.random.default_rng(seed)
    langs = sorted(set(labels))
    net = ByteNet.fresh(langs, rng)
    rows, target = [], []
    for text, lang in zip(texts, labels):
        data = text.encode()
        if not data:
            continue
        whole = windows_of(data)
        pick = whole[rng.permutation(len(whole))[:3]]
        rows.extend(pick)
        words = text.split()
        for _ in range(2):
            at, n = int(rng.integers(0, max(1, len(words)))), int(rng.integers(1, 12))
            rows.append(windows_of(" ".join(words[at : at + n]).encode()[:WINDOW])[0])
        target += [langs.index(lang)] * (len(pick) + 2)
    if not rows:
        return net
    x, y = np.stack(rows), np.array(target)
    first = [np.zeros_like(p) for p in net.parameters()]
    second = [np.zeros_like(p) for p in net.parameters()]
    step, steps = 0, epochs * -(-len(x) // BATCH)
    for _ in range(epochs):
        order = rng.permutation(len(x))
        for at in range(0, len(x), BATCH):
            pick = order[at : at + BATCH]
            step += 1
            rate = RATE * (1 - (step - 1) / steps)
            for p, g, m, v in zip(net.parameters(), net.gradients(x[pick], y[pick]), first, second):
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                p -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-7)
    return net


def spread_out(text: Column, stretches: int = TRAIN_WINDOWS, size: int = STRETCH) -> Column:
    """All of a short text; of a longer one stretches of its characters, evenly spread from its begin to its end."""
    step = (F.length(text) - size) / F.lit(stretches - 1)
    parts = F.transform(F.sequence(F.lit(0), F.lit(stretches - 1)), lambda i: F.substring(text, F.floor(i * step).cast("int") + 1, F.lit(size)))
    return F.when(F.length(text) <= stretches * size, text).otherwise(F.array_join(parts, " "))


def train(labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample: int = SAMPLE) -> ByteNet:
    """Fit on at most ``sample`` rows of each language, those of smallest hash of the id; rows without text or language take no part."""
    rows = labelled.where(F.col(text_col).isNotNull() & F.col(lang_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.xxhash64(F.col(id_col).cast("string")).alias("h"), F.col(text_col).alias("text"))
    per = rows.groupBy("lang").count()  # one row a language
    share = (per["count"].cast("double") / (1.3 * sample)).alias("of")  # a threshold of the hash leaves little to sort
    near = rows.join(sized(per.select(F.col("lang").alias("l"), share)), F.col("lang") == F.col("l"))
    taken = near.where(F.pmod("h", F.lit(1_000_000)) * F.col("of") <= 1_000_000).select("lang", "h", spread_out(F.col("text")).alias("text"))
    from pyspark.sql import Window as W

    rank = F.row_number().over(W.partitionBy("lang").orderBy("h", "text"))
    got = taken.withColumn("r", rank).where(F.col("r") <= sample).orderBy("lang", "r").collect()
    if not got:
        return ByteNet.fresh(["und"], np.random.default_rng(SEED))
    return fit([r["text"] for r in got], [r["lang"] for r in got])


def predict(net: ByteNet, texts: list[str | None], most: int = 64) -> tuple[list[str], list[float]]:
    """(language, score) of whole texts. ``und`` with score 0 where there is no letter."""
    rows, owner, weight, known = [], [], [], []
    for n, text in enumerate(texts):
        known.append(bool(text) and LETTER.search(text) is not None)
        if known[-1]:
            data = text.encode()
            cut = windows_of(data)
            rows.append(cut)
            owner.append(np.full(len(cut), n))
            w = np.full(len(cut), WINDOW, np.float64)
            w[-1] = len(data) - WINDOW * (len(cut) - 1)
            weight.append(w)
    total, mass = np.zeros((len(texts), len(net.langs))), np.zeros(len(texts))
    if rows:
        x, o, w = np.concatenate(rows), np.concatenate(owner), np.concatenate(weight)
        for at in range(0, len(x), most):
            p = np.exp(net.log_probs(x[at : at + most]))
            np.add.at(total, o[at : at + most], p * w[at : at + most, None])
            np.add.at(mass, o[at : at + most], w[at : at + most])
    p = np.minimum(total / np.maximum(mass, 1)[:, None], 1.0)
    best = p.argmax(axis=1)
    return [net.langs[b] if k else "und" for b, k in zip(best, known)], [float(p[n, b]) if k else 0.0 for n, (b, k) in enumerate(zip(best, known))]


def _applier(net: ByteNet, names: list[str], text_at: int):  # noqa: ANN202
    """The columns ``names`` of each batch with the prediction for the one at ``text_at``, which may be one of them or stand behind them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.slice(at, 256)
                lang, score = predict(net, part.column(text_at).to_pylist())
                yield pa.RecordBatch.from_arrays([*part.columns[: len(names)], pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=[*names, "lang_pred", "score"])

    return run


def identify(docs: DataFrame, net: ByteNet, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """The ``keep`` columns with lang_pred and score (0 to 1) of every whole text.

    Only the text is looked at. Null texts and texts without a letter get ``und`` and 0; ties go to the language that
    sorts first; repeated rows and null ids stay; an empty frame gives an empty one.
    """
    schema = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keep) + ", lang_pred string, score double"
    if text_col in keep and docs.schema[text_col].dataType.simpleString() == "string":  # so that no text goes to a worker twice
        return docs.select(*keep).mapInArrow(lean(_applier(net, list(keep), keep.index(text_col))), schema)
    return docs.select(*keep, F.col(text_col).cast("string").alias("__text")).mapInArrow(lean(_applier(net, list(keep), len(keep))), schema)


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))
    net = train(docs.where(~held))
    return identify(docs.select("doc_id", held.alias("held_out"), "text"), net, ("doc_id", "held_out"))
