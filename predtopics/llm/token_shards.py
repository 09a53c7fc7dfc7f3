"""Token ids in binary shards with a minimal perfect hash index, and keyed access to them.

A shard is one row of a Parquet file in the shared folder: raw little-endian ids of consecutive documents
(two bytes an id where the vocabulary fits, else four), their keys in order, and an index. The index is a
minimal perfect hash: keys go through levels of bit arrays, each key is placed at the first level where it is
alone on its bit, and its slot is the number of bits set before that bit. A slot holds a 32-bit fingerprint
of its key, the offset and the number of ids, so one key costs a few hashes and one read of a slot whatever
the shard's size, and unknown keys are told by their fingerprints (an error rate of about 2^-32).

Documents are range-partitioned by key on the plain table, sorted, tokenised as they stream past and cut into
shards of bounded size, so no shard or task holds more than ``SHARD_IDS`` ids besides one document.
"""

from __future__ import annotations

import json
import re
import uuid
import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W
from tokenizers import Tokenizer

from .bpe import byte_alphabet
from .common import shared_dir, sized, table
from .memo import Memo

#: Bytes in which a worker remembers repeated parts of texts.
MEMO = 192 << 20
#: Letters a-z and those of U+00C0 to U+00FF, none of which composes with another, in UTF-8.
LETTERS = rb"(?:[a-z]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+"
WORD = re.compile(LETTERS)
#: A part that is a word with marks behind it; no token crosses from a letter to an ASCII mark other than an apostrophe.
MARKED = re.compile(rb"(" + LETTERS + rb"|[a-z\x80-\xff]*[a-z])([!-&(-/:-@\[-`{-~]+)")
#: How a tokenizer takes texts apart if a part of nothing but letters is, in lower case, one word of its model.
WHOLE_WORDS = (
    {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]},
    {"type": "Sequence", "pretokenizers": [
        {"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True},
        {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
    ]},
)
#: Ids after which a shard is closed.
SHARD_IDS = 2_000_000
#: Bits of a level for each key that has come to it.
GAMMA = 2.0
SHARD_SCHEMA = "part int, seq int, first_key long, last_key long, n_docs long, n_ids long, width int, payload binary, nulls binary, keys binary, repeats binary, hash_sizes binary, hash_bits binary, slots binary"


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class LibraryIds:
    """The library's ids of whole texts, by way of their parts between ASCII white space, which no token crosses.

    For a tokenizer that lower-cases and drops white space, as the default one does. Parts of letters alone, by far the most,
    are given to the library's model at once: the steps before it, and the making of offsets and masks, cost several times what the model does.
    """

    def __init__(self, path: str, end_id: int | None, memo: int = MEMO) -> None:
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.width = 2 if self.library.get_vocab_size(with_added_tokens=True) <= 1 << 16 else 4
        self.end = b"" if end_id is None else np.array([end_id], f"<u{self.width}").tobytes()
        self.kind = "H" if self.width == 2 else "I"
        self.memo = Memo(self._one, memo)
        self.whole = self._steps() == WHOLE_WORDS and self.library.post_processor is None
        self.shown = str.maketrans({b: c for c, b in byte_alphabet().items()})
        self.tokenize = self.library.model.tokenize

    def _steps(self) -> tuple:
        """The steps before the model, as the tokenizer's file has them."""
        return tuple(step and json.loads(step.__getstate__()) for step in (self.library.normalizer, self.library.pre_tokenizer))

    def _word(self, part: bytes) -> bytes:
        word = part.decode().lower()
        if not part.isascii():
            word = word.encode().decode("latin-1").translate(self.shown)
        return array(self.kind, [token.id for token in self.tokenize(word)]).tobytes()

    def _one(self, part: bytes) -> bytes:
        if self.whole and (part.isalpha() or WORD.fullmatch(part)):
            return self._word(part)
        if cut := MARKED.fullmatch(part):
            return self.memo[cut[1]] + self.memo[cut[2]]
        return array(self.kind, self.library.encode(part.decode(), add_special_tokens=False).ids).tobytes()

    def encode(self, text: str) -> bytes:
        data = text.encode()
        if b"<|" not in data:  # the tokenizer's own lower-casing comes after it has looked for special tokens
            data = data.lower()
        return b"".join(map(self.memo.__getitem__, data.split())) + self.end


@lru_cache(maxsize=2)
def _ids(path: str, end_id: int | None) -> LibraryIds:
    return LibraryIds(path, end_id)


def mix(keys: np.ndarray, salt: int) -> np.ndarray:
    """64-bit finaliser of keys under a salt."""
    with np.errstate(over="ignore"):
        x = keys + np.uint64((0x9E3779B97F4A7C15 * (salt + 1)) & (2**64 - 1))
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def hashed(keys: np.ndarray, repeats: np.ndarray) -> np.ndarray:
    """What is indexed: a key together with how often it has come before."""
    return mix(keys.astype(np.int64).view(np.uint64), 101) ^ mix(repeats.astype(np.uint64), 202)


class PerfectHash:
    """Minimal perfect hash of distinct 64-bit values: levels of bits, and ones before each 64-bit word."""

    def __init__(self, sizes: np.ndarray, bits: np.ndarray) -> None:
        self.sizes, self.bits = sizes.astype(np.int64), bits.view(np.uint64)
        self.start = np.concatenate([[0], np.cumsum(self.sizes)])
        self.before = np.concatenate([[0], np.cumsum(np.bitwise_count(self.bits).astype(np.int64))])

    @classmethod
    def build(cls, values: np.ndarray) -> PerfectHash:
        sizes, words, left, level = [], [], values, 0
        while len(left):
            size = 64 * max(1, int(np.ceil(GAMMA * len(left) / 64)))
            at = (mix(left, level) % np.uint64(size)).astype(np.int64)
            alone = np.bincount(at, minlength=size) == 1
            words.append(np.packbits(alone, bitorder="little").view("<u8"))
            sizes.append(size)
            left, level = left[~alone[at]], level + 1
            if level > 200:
                raise ValueError("keys of a shard are not distinct")
        return cls(np.array(sizes, np.int64), np.concatenate(words) if words else np.zeros(0, np.uint64))

    def slots(self, values: np.ndarray) -> np.ndarray:
        """Slot of each value; -1 for one that no level has."""
        out = np.full(len(values), -1, np.int64)
        todo = np.arange(len(values))
        for level, size in enumerate(self.sizes.tolist()):
            if not len(todo):
                break
            at = self.start[level] + (mix(values[todo], level) % np.uint64(size)).astype(np.int64)
            word, bit = at >> 6, (at & 63).astype(np.uint64)
            here = (self.bits[word] >> bit) & np.uint64(1) == 1
            w, b = word[here], bit[here]
            out[todo[here]] = self.before[w] + np.bitwise_count(self.bits[w] & ((np.uint64(1) << b) - np.uint64(1))).astype(np.int64)
            todo = todo[~here]
        return out


def _print32(values: np.ndarray) -> np.ndarray:
    return (mix(values, 999) >> np.uint64(32)).astype(np.uint32)


def shard_row(part: int, seq: int, keys: list[int | None], ids: list[bytes], width: int, held: dict) -> dict:
    """One shard's row. Null keys are in the payload, in order, but not in the index. held: the last key so far and its repeats."""
    known = np.array([k is not None for k in keys], bool)
    number = np.array([k or 0 for k in keys], np.int64)
    repeats = np.zeros(len(keys), np.int64)
    for n, k in enumerate(keys):
        held["n"] = held["n"] + 1 if k == held.get("key", object()) else 0
        held["key"], repeats[n] = k, held["n"]
    size = np.array([len(x) // width for x in ids], np.int64)
    offset = np.concatenate([[0], np.cumsum(size)[:-1]]).astype(np.int64)
    values = hashed(number, repeats)[known]
    index = PerfectHash.build(values)
    slot = index.slots(values)
    slots = np.zeros(len(values), [("print", "<u4"), ("offset", "<u4"), ("size", "<u4")])
    slots["print"][slot], slots["offset"][slot], slots["size"][slot] = _print32(values), offset[known], size[known]
    some = number[known]
    return {
        "part": part, "seq": seq, "first_key": int(some[0]) if len(some) else None, "last_key": int(some[-1]) if len(some) else None, "n_docs": len(keys), "n_ids": int(size.sum()), "width": width,
        "payload": b"".join(ids), "nulls": size[~known].tobytes(), "keys": number[known].tobytes(), "repeats": repeats[known].astype(np.int32).tobytes(), "hash_sizes": index.sizes.tobytes(), "hash_bits": index.bits.tobytes(), "slots": slots.tobytes(),
    }


def _writer(path: str, end_id: int | None, most: int):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = _ids(path, end_id)
        part, seq, held = TaskContext.get().partitionId(), 0, {"n": 0}
        names = [x.split()[0] for x in SHARD_SCHEMA.split(", ")]
        types = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
        kinds = [types[x.split()[1]] for x in SHARD_SCHEMA.split(", ")]
        keys: list = []
        ids: list[bytes] = []
        total = 0

        def close() -> pa.RecordBatch:
            row = shard_row(part, seq, keys, ids, coder.width, held)
            return pa.RecordBatch.from_arrays([pa.array([row[n]], k) for n, k in zip(names, kinds)], names=names)

        for batch in batches:
            for key, text in zip(batch.column(0), batch.column(1)):
                keys.append(key.as_py())
                ids.append(coder.encode(text.as_py() or ""))
                total += len(ids[-1]) // coder.width
                if total >= most:
                    yield close()
                    keys, ids, total, seq = [], [], 0, seq + 1
        if keys:
            yield close()

    return run


def write_shards(docs: DataFrame, out: str, path: str | None = None, end_id: int | None = 1, id_col: str = "doc_id", text_col: str = "text", shard_ids: int = SHARD_IDS) -> str:
    """Encode every whole text and write the ids to ``out`` in ascending key order; returns ``out``.

    Keys are whole numbers. Null keys come first; repeated keys keep all their rows, told apart by how often the key
    came before (rows of one key in the order of their texts). Null texts are empty ones: only the end id. An empty frame gives
    no shards. Other columns are ignored.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).cast("string").alias("text"))
    dealt = rows.repartitionByRange("key").sortWithinPartitions("key", "text")
    dealt.mapInArrow(_writer(path or default_vocabulary(), end_id, shard_ids), SHARD_SCHEMA).write.mode("overwrite").option("compression", "snappy").parquet(out)
    return out


def shard_starts(shards: DataFrame) -> DataFrame:
    """(part, seq, start): ids in all shards before one. Parts are as many as tasks wrote; within a part shards are few."""
    sizes = shards.select("part", "seq", "n_ids")
    parts = sizes.groupBy("part").agg(F.sum("n_ids").alias("n"))
    parts = parts.withColumn("ahead", F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, W.currentRow)) - F.col("n")).select("part", "ahead")
    within = F.sum("n_ids").over(W.partitionBy("part").orderBy("seq").rowsBetween(W.unboundedPreceding, W.currentRow)) - F.col("n_ids")
    return sizes.withColumn("inside", within).join(F.broadcast(parts), "part").select("part", "seq", (F.col("ahead") + F.col("inside")).alias("start"))


class Shard:
    """Keyed access to one shard's ids."""

    def __init__(self, row: dict) -> None:
        self.ids = np.frombuffer(row["payload"], f"<u{row['width']}")
        self.index = PerfectHash(np.frombuffer(row["hash_sizes"], np.int64), np.frombuffer(row["hash_bits"], np.uint64))
        self.slots = np.frombuffer(row["slots"], [("print", "<u4"), ("offset", "<u4"), ("size", "<u4")])

    def find(self, keys: np.ndarray, repeats: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(found, offset, size) of each key."""
        values = hashed(keys, repeats)
        slot = self.index.slots(values)
        if not len(self.slots):
            return np.zeros(len(keys), bool), slot, slot
        got = self.slots[np.maximum(slot, 0)]
        return (slot >= 0) & (got["print"] == _print32(values)), got["offset"].astype(np.int64), got["size"].astype(np.int64)


def _reader(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            shard = Shard(row)
            keys, repeats = np.frombuffer(row["keys"], np.int64), np.frombuffer(row["repeats"], np.int32)
            found, offset, size = shard.find(keys, repeats)
            if not found.all():
                raise ValueError(f"shard {row['part']}.{row['seq']} does not find its own keys")
            lead = np.frombuffer(row["nulls"], np.int64)  # rows without a key come first
            offset = np.concatenate([np.cumsum(lead) - lead, offset])
            size = np.concatenate([lead, size])
            ids = [shard.ids[o : o + n] for o, n in zip(offset.tolist(), size.tolist())]
            keys = [None] * len(lead) + keys.tolist()
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(keys, pa.int64()), pa.array(row["start"] + offset), pa.array(size),
                    pa.array([zlib.crc32(x.astype("<u4").tobytes()) for x in ids], pa.int64()), pa.array([x.astype("<u4").tobytes() for x in ids], pa.binary()),
                ], names=["doc_id", "start", "n_tokens", "ids_crc32", "ids"],
            )


def read_all(spark: SparkSession, path: str) -> DataFrame:
    """Every document of the shards by way of their indexes: (doc_id, start, n_tokens, ids_crc32, ids as little-endian 32-bit)."""
    shards = spark.read.parquet(path)
    placed = shards.join(sized(shard_starts(shards)), ["part", "seq"])
    return placed.mapInArrow(_reader, "doc_id long, start long, n_tokens long, ids_crc32 long, ids binary")


def _lookup(key, left, right):  # noqa: ANN001
    """The wanted keys of one shard against it."""
    import pandas as pd

    if not len(left) or not len(right):
        return pd.DataFrame({"key": pd.Series(dtype="int64"), "ids": pd.Series(dtype=object)})
    shard = Shard(left.iloc[0].to_dict())
    keys = right["key"].to_numpy(np.int64)
    found, offset, size = shard.find(keys, np.zeros(len(keys), np.int64))
    return pd.DataFrame({"key": keys[found], "ids": [shard.ids[o : o + n].astype("<u4").tobytes() for o, n in zip(offset[found].tolist(), size[found].tolist())]})


def lookup(spark: SparkSession, path: str, keys: DataFrame, key_col: str = "key") -> DataFrame:
    """(key, ids) of the wanted keys that the shards have (of a repeated key its first row). Only shards whose range holds a wanted key are read."""
    shards = spark.read.parquet(path)
    ranges = shards.where("first_key is not null").select("part", "seq", "first_key", "last_key")
    want = keys.select(F.col(key_col).cast("long").alias("key")).where("key is not null").distinct()
    routed = want.join(ranges, (F.col("key") >= F.col("first_key")) & (F.col("key") <= F.col("last_key"))).select(F.col("part").alias("p"), F.col("seq").alias("s"), "key")
    return shards.groupBy("part", "seq").cogroup(routed.groupBy("p", "s")).applyInPandas(_lookup, "key long, ids binary")


def op8_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = write_shards(table(spark, sf_dir, "documents", "doc_id", "text"), f"{shared_dir(spark)}/token-shards-{uuid.uuid4().hex}")
    return read_all(spark, out).select("doc_id", "start", "n_tokens", "ids_crc32")
