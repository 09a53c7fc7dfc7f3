"""Quality by perplexity under an interpolated modified Kneser-Ney model of byte n-grams, trained on trusted text.

n-grams of ``ORDER`` bytes are whole numbers (8 bits a byte), so counting is sorting, and shorter n-grams are remainders. Counts of
trusted text are summed over shards by n-gram; lower orders count how many bytes an n-gram was seen
behind (its continuations), and each order's discounts come from its counts of counts. Probabilities go up the orders
by joins of the sharded tables on n-grams and contexts.

For scoring, the n-grams of all documents are counted the same way and joined with the sharded tables: that gives the
log-probability of every n-gram that occurs. If these are at most ``MOST`` (their size is known then) every worker gets them as
sorted arrays and reads the documents where they are. Beyond that, each block of documents asks for its own n-grams by a join, and is
scored next to the answers. A text begins behind ORDER-1 zero bytes.

Thresholds are quantiles by language over all trusted texts, each scored by a model that has not seen it: trusted documents are dealt
to ``HELD`` folds by a hash of the id, and each fold is scored by the model of the others. All other documents are scored by the
model that does without the first fold, so they and the trusted ones stand behind models of the same share of trusted text. These models are
trained at once: each sharded table has a column for each of them, as the counts without a fold are all counts less that fold's.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checkpoint, shared_dir, sized, table

ORDER = 5
#: Distinct n-grams that workers may hold (8 bytes, and 4 for each model), and bytes of text that are sorted at once.
MOST, CHUNK = 4_000_000, 8 << 20
#: Quantile of trusted text's perplexity, by language, up to which a document is kept.
QUANTILE = 0.995
#: Folds of trusted documents; a model is trained on all but one.
HELD = 3


def grams(data: bytes, order: int = ORDER) -> np.ndarray:
    """n-grams of a text, one for each byte."""
    x = np.frombuffer(b"\0" * (order - 1) + data, np.uint8).astype(np.int64)
    n = len(data)
    out = np.zeros(n, np.int64)
    for k in range(order):
        out = out << 8 | x[k : k + n]
    return out


def _add(held: tuple[np.ndarray, np.ndarray] | None, new: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    keys, counts = np.unique(new, return_counts=True)
    if held is None:
        return keys, counts
    both, inverse = np.unique(np.concatenate([held[0], keys]), return_inverse=True)
    total = np.zeros(len(both), np.int64)
    np.add.at(total, inverse, np.concatenate([held[1], counts]))
    return both, total


def _count(order: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, tuple] = {}
        waiting: dict[int, list[np.ndarray]] = {}
        size = 0

        def add() -> None:
            for fold, new in waiting.items():
                held[fold] = _add(held.get(fold), np.concatenate(new))
            waiting.clear()

        def out() -> Iterator[pa.RecordBatch]:
            for fold, (keys, counts) in held.items():
                if len(keys):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), fold, np.int32)), pa.array(keys), pa.array(counts.astype(np.int64))], names=["fold", "gram", "c"])
            held.clear()

        for batch in batches:
            for fold, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                data = (text.as_py() or "").encode()
                for at in range(0, len(data), CHUNK):
                    g = grams(data[max(0, at - order + 1) : at + CHUNK], order)
                    waiting.setdefault(fold, []).append(g if not at else g[order - 1 :])
                size += len(data)
                if size >= CHUNK:
                    add()
                    size = 0
                    if sum(len(k) for k, _ in held.values()) > 3_000_000:
                        yield from out()
        add()
        yield from out()

    return run


def counted(texts: DataFrame, order: int = ORDER, text_col: str = "text", fold: Column | None = None, folds: int = 1) -> DataFrame:
    """(gram, f0, f1, ...) over all texts: counts by fold, a whole number below ``folds``; without it, all are in the first."""
    number = F.lit(0) if fold is None else fold
    some = texts.where(F.col(text_col).isNotNull()).select(number.cast("int").alias("fold"), F.col(text_col).cast("string").alias("text"))
    found = some.mapInArrow(_count(order), "fold int, gram long, c long")
    return found.groupBy("gram").agg(*[F.sum(F.when(F.col("fold") == k, F.col("c")).otherwise(0)).cast("long").alias(f"f{k}") for k in range(folds)])


def discounts(ones: int, twos: int, threes: int, fours: int) -> tuple[float, float, float]:
    """Discounts of counts 1, 2 and 3 or more, from how many n-grams have counts 1 to 4; 0.5, 0.75 and 0.9 where any of these is none."""
    if min(ones, twos, threes, fours) <= 0:
        return 0.5, 0.75, 0.9
    y = ones / (ones + 2 * twos)
    d = (1 - 2 * y * twos / ones, 2 - 3 * y * threes / twos, 3 - 4 * y * fours / threes)
    return tuple(min(max(x, 0.05), k - 0.05) for k, x in zip((1, 2, 3), d))


class Model:
    """Sharded tables by order, with a column for each of ``n`` models: probabilities of n-grams (gram, p0, ...) that any has seen, and what contexts give back (context, gamma0, ...)."""

    def __init__(self, probs: dict[int, DataFrame], gammas: dict[int, DataFrame], order: int, n: int) -> None:
        self.probs, self.gammas, self.order, self.n = probs, gammas, order, n


def _tail(gram, k: int):  # noqa: ANN001, ANN202
    return F.col(gram).bitwiseAND(F.lit((1 << 8 * k) - 1))


def train(trusted: DataFrame, order: int = ORDER, text_col: str = "text", fold: Column | None = None, folds: int = 1) -> Model:
    """The model of trusted texts; given folds, for each of them the model of all others, or its own if the others have no text.

    Null and empty texts add nothing; without any text all bytes are equally likely.
    """
    raw = checkpoint(counted(trusted, order, text_col, fold, folds))
    sums = [x or 0 for x in raw.agg(*[F.sum(f"f{k}") for k in range(folds)]).first()]
    columns = []
    for k in range(folds):
        others = [f"f{j}" for j in range(folds) if j != k] if sum(sums) > sums[k] else [f"f{j}" for j in range(folds)]
        columns.append(sum((F.col(f) for f in others[1:]), F.col(others[0])).alias(f"n{k}"))
    models = range(folds)
    counts = {order: raw.select("gram", *columns)}
    for k in range(order - 1, 0, -1):
        counts[k] = counts[k + 1].groupBy(_tail("gram", k).alias("gram")).agg(*[F.count_if(F.col(f"n{i}") > 0).alias(f"n{i}") for i in models])
        if k == order - 1:
            counts[k] = checkpoint(counts[k])
    probs, gammas, lower = {}, {}, None
    for k in range(1, order + 1):
        c = counts[k].withColumn("context", F.shiftright("gram", 8))
        of = c.agg(*[F.count_if(F.col(f"n{i}") == x).alias(f"n{i}_{x}") for i in models for x in (1, 2, 3, 4)]).first()
        cut = []
        for i in models:
            d, n = discounts(*of[4 * i : 4 * i + 4]), F.col(f"n{i}")
            cut.append(F.when(n == 0, 0.0).when(n == 1, d[0]).when(n == 2, d[1]).otherwise(d[2]))
        total = c.groupBy("context").agg(*[F.sum(f"n{i}").alias(f"total{i}") for i in models], *[F.sum(cut[i]).alias(f"cut{i}") for i in models])
        gammas[k] = checkpoint(total.select("context", *[f"total{i}" for i in models], *[F.when(F.col(f"total{i}") > 0, F.col(f"cut{i}") / F.col(f"total{i}")).alias(f"gamma{i}") for i in models]))
        seen = c.join(sized(gammas[k]), "context")
        if lower is not None:
            seen = seen.join(sized(lower.select(F.col("gram").alias("tail"), *[F.col(f"p{i}").alias(f"below{i}") for i in models])), _tail("gram", k - 1) == F.col("tail"))
        p = []
        for i in models:
            below = F.lit(1 / 256) if lower is None else F.col(f"below{i}")
            p.append(F.when(F.col(f"total{i}") > 0, (F.col(f"n{i}") - cut[i]) / F.col(f"total{i}") + F.col(f"gamma{i}") * below).otherwise(below).alias(f"p{i}"))
        probs[k] = lower = checkpoint(seen.select("gram", *p))
    return Model(probs, gammas, order, folds)


def log_probs(model: Model, wanted: DataFrame) -> DataFrame:
    """(gram, logp, logp1, ...) of distinct n-grams of the model's order, seen or not, by each of its models."""
    models = range(model.n)
    p = [F.lit(1 / 256)] * model.n
    cur = wanted.select("gram")
    for k in range(1, model.order + 1):
        seen = model.probs[k].select(F.col("gram").alias("g"), *[F.col(f"p{i}").alias(f"s{i}") for i in models])
        back = model.gammas[k].select(F.col("context").alias("h"), *[F.col(f"gamma{i}").alias(f"b{i}") for i in models])
        cur = cur.join(sized(seen), _tail("gram", k) == F.col("g"), "left").join(sized(back), F.shiftright(_tail("gram", k), 8) == F.col("h"), "left")
        cur = cur.select("gram", *[F.coalesce(F.col(f"s{i}"), F.coalesce(F.col(f"b{i}"), F.lit(1.0)) * p[i]).alias(f"q{i}") for i in models])
        p = [F.col(f"q{i}") for i in models]
    return cur.select("gram", *[F.log(p[i]).cast("float").alias(f"logp{i or ''}") for i in models])


def _sums(texts: list[bytes], which: np.ndarray, keys: np.ndarray, logs: np.ndarray, order: int) -> list[float]:
    """Sum of log-probabilities of each text by the model that ``which`` gives it."""
    out = []
    for data, model in zip(texts, which):
        total = 0.0
        for at in range(0, len(data), CHUNK):
            g = grams(data[max(0, at - order + 1) : at + CHUNK], order)
            total += float(logs[model][np.searchsorted(keys, g if not at else g[order - 1 :])].sum(dtype=np.float64))
        out.append(total)
    return out


def _packed(texts: list[bytes], which: np.ndarray, keys: np.ndarray, logs: np.ndarray, order: int) -> list[float]:
    """As _sums, for many texts at once: the n-grams of some megabytes are made distinct before they are looked up."""
    out: list[float] = []
    first = 0

    def settle(last: int) -> None:
        nonlocal first
        g = [grams(t, order) for t in texts[first:last]]
        size = np.array([len(x) for x in g], np.int64)
        if size.sum():
            seen, inverse = np.unique(np.concatenate(g), return_inverse=True)
            found = logs[np.repeat(which[first:last], size), np.searchsorted(keys, seen)[inverse]]
            values = np.concatenate([[0.0], np.cumsum(found, dtype=np.float64)])
            ends = np.cumsum(size)
            out.extend((values[ends] - values[ends - size]).tolist())
        else:
            out.extend([0.0] * len(size))
        first = last

    size = 0
    for n, data in enumerate(texts):
        if len(data) > CHUNK:
            settle(n)
            out.extend(_sums([data], which[n : n + 1], keys, logs, order))
            first, size = n + 1, 0
            continue
        size += len(data)
        if size > CHUNK // 8:
            settle(n + 1)
            size = 0
    settle(len(texts))
    return out


def _scorer(held, order: int, names: list[str]):  # noqa: ANN001, ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, logs = held.value
        for batch in batches:
            for at in range(0, len(batch), 2048):
                part = batch.slice(at, 2048)
                texts = [(t.as_py() or "").encode() for t in part.column(part.num_columns - 1)]
                which = part.column(part.num_columns - 2).to_numpy(zero_copy_only=False)
                size = np.array([len(t) for t in texts], np.int64)
                sums = np.array(_packed(texts, which, keys, logs, order))
                yield pa.RecordBatch.from_arrays([*part.columns[:-2], pa.array(size), pa.array(sums, pa.float64())], names=[*names, "n_bytes", "log_sum"])

    return run


def _ask(order: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(block, text) sorted by block -> the distinct n-grams of each block."""
        for batch in batches:
            block = batch.column(0).to_numpy()
            texts = batch.column(1).to_pylist()
            for b in np.unique(block):
                g = np.unique(np.concatenate([grams((texts[i] or "").encode(), order) for i in np.flatnonzero(block == b)]))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(g), b)), pa.array(g)], names=["block", "gram"])

    return run


def _near(order: int, names: list[str], columns: list[str]):  # noqa: ANN202
    def run(key, docs, answers):  # noqa: ANN001, ANN202
        import pandas as pd

        answers = answers.sort_values("gram")
        data = [(t or "").encode() for t in docs["__text"]]
        logs = answers[columns].to_numpy(np.float32).T
        sums = _sums(data, docs["__model"].to_numpy(), answers["gram"].to_numpy(), logs, order)
        return pd.concat([docs[names].reset_index(drop=True), pd.DataFrame({"n_bytes": np.array([len(d) for d in data], np.int64), "log_sum": sums})], axis=1)

    return run


def perplexity(docs: DataFrame, model: Model, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text", most: int = MOST, which: Column | None = None) -> DataFrame:
    """The ``keep`` columns with n_bytes and perplexity (per byte) of every whole text; null for null and empty texts.

    ``which`` tells by which of the model's models a row is scored; without it, by the first.
    """
    spark, order = docs.sparkSession, model.order
    known = checkpoint(log_probs(model, counted(docs, order, text_col).select("gram")))
    columns = [c for c in known.columns if c != "gram"]
    number = (F.lit(0) if which is None else which).cast("int").alias("__model")
    rows = docs.select(*keep, number, F.col(text_col).cast("string").alias("__text"))
    schema = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keep) + ", n_bytes long, log_sum double"
    if known.limit(most + 1).count() <= most:
        got = known.toArrow()  # 8 bytes an n-gram and 4 for each model
        keys = got["gram"].to_numpy()
        order_of = np.argsort(keys)
        logs = np.stack([got[c].to_numpy().astype(np.float32)[order_of] for c in columns]) if len(keys) else np.zeros((len(columns), 0), np.float32)
        held = spark.sparkContext.broadcast((keys[order_of], logs))
        del got, keys, logs
        scored = rows.mapInArrow(_scorer(held, order, list(keep)), schema)
    else:
        blocks = max(1, int((rows.agg(F.sum(F.octet_length("__text"))).first()[0] or 0) / (4 * CHUNK)))
        at = f"{shared_dir(spark)}/blocks-{uuid.uuid4().hex}"  # written, so that a row's block stays the same
        rows.withColumn("block", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(blocks))).write.parquet(at)
        placed = spark.read.parquet(at)
        answers = placed.select("block", "__text").mapInArrow(_ask(order), "block long, gram long").distinct().join(known, "gram")
        scored = placed.groupBy("block").cogroup(answers.select(F.col("block").alias("at"), "gram", *columns).groupBy("at")).applyInPandas(_near(order, list(keep), columns), schema)
    return scored.withColumn("perplexity", F.when(F.col("n_bytes") > 0, F.exp(-F.col("log_sum") / F.col("n_bytes")))).drop("log_sum")


def thresholds(scored: DataFrame, by: str = "trusted", lang: str = "lang", quantile: float = QUANTILE) -> DataFrame:
    """(lang, threshold, n): by language, and a row of null language for all rows of ``by`` together."""
    rows = scored.where(F.col(by) & F.col("perplexity").isNotNull())
    value = [F.percentile_approx("perplexity", quantile, 10_000).alias("threshold"), F.count("*").alias("n")]
    each = rows.where(F.col(lang).isNotNull()).groupBy(F.col(lang).alias("lang")).agg(*value)
    return each.unionByName(rows.agg(*value).select(F.lit(None).cast("string").alias("lang"), "threshold", "n"))


def classify(docs: DataFrame, trusted_ids: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", quantile: float = QUANTILE, most: int = MOST) -> DataFrame:
    """(doc_id, lang, trusted, n_bytes, perplexity, threshold, keep) of every row.

    Trained on the rows whose id is in ``trusted_ids`` (its first column); if all of them fall into one fold, its own text is what there is to
    train on. A language without trusted text, and a null one, has
    the threshold of all trusted text; null and empty texts have no perplexity and are not kept; without trusted text there is no threshold
    and every text is kept. Repeated rows and null ids stay; an empty frame gives an empty one. Other columns are ignored.
    """
    ids = trusted_ids.select(F.col(trusted_ids.columns[0]).alias("__id")).where("__id is not null").distinct()
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text"))
    marked = rows.join(sized(ids.withColumn("__in", F.lit(True)), 2_000_000), F.col("doc_id") == F.col("__id"), "left").select("doc_id", "lang", "text", F.coalesce("__in", F.lit(False)).alias("trusted"))
    fold = F.pmod(F.xxhash64(F.col("doc_id").cast("string")), F.lit(HELD))
    marked = marked.withColumn("fold", F.when(F.col("trusted"), fold).otherwise(F.lit(0)).cast("int"))
    model = train(marked.where("trusted"), fold=F.col("fold"), folds=HELD)
    scored = checkpoint(perplexity(marked, model, ("doc_id", "lang", "trusted"), "text", most, F.col("fold")))
    limit = checkpoint(thresholds(scored, quantile=quantile))
    every = limit.where("lang is null").first()["threshold"]
    own = limit.where("lang is not null").select(F.col("lang").alias("__lang"), "threshold")
    out = scored.join(sized(own), F.col("lang") == F.col("__lang"), "left")
    out = out.withColumn("threshold", F.coalesce("threshold", F.lit(every).cast("double")))
    keep = F.col("perplexity").isNotNull() & (F.col("threshold").isNull() | (F.col("perplexity") <= F.col("threshold")))
    return out.select("doc_id", "lang", "trusted", "n_bytes", "perplexity", "threshold", keep.alias("keep"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels", "doc_id", "quality", "toxic")
    trusted = labels.where((F.col("quality") == 1) & (F.coalesce("toxic", F.lit(0)) == 0)).select("doc_id")
    return classify(table(spark, sf_dir, "documents", "doc_id", "lang", "text"), trusted)
