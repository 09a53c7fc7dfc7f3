"""Byte-level BPE: encoding by a priority queue of merge ranks over a doubly linked symbol list, and decoding.

A text is cut at special tokens, then into pieces. Every piece is a list of byte symbols linked both ways;
the queue holds (rank, position) of adjacent pairs, the lowest rank first and the leftmost among equals.
Popping an entry whose pair is no longer there skips it; otherwise the right symbol is joined into the left one and
the two new neighbours are queued. A piece of n bytes takes O(n log n), so very long pieces are no trouble.
New pieces of at most ``SHORT`` bytes are merged many at a time: their lists and queues are columns of arrays, and each step
pops the first entry of every queue. Values of repeated pieces come from a memo that is bounded in bytes.
A worker encodes and decodes in one pass.
"""

from __future__ import annotations

import heapq
import json
import re
from array import array
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from .common import lean, table
from .memo import LONG, Memo

#: White space as the pattern of byte-level BPE has it.
WHITE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Bytes in which a worker remembers repeated pieces of texts.
MEMO = 88 << 20
#: Up to this code point all Unicode versions agree on letters and numbers; others are left to the library's own splitter.
AGREED = "\u0557"
#: Most bytes of a piece that is merged with others in arrays (a power of two), pieces that are merged at once, and the fewest that are.
SHORT, ROWS, FEW = 32, 1 << 13, 64
#: The key of a queue's entry that is none.
NONE = np.iinfo(np.int32).max


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def byte_alphabet() -> dict[str, int]:
    """Printable stand-in of each byte, as byte-level vocabularies write it."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


def vocabulary_strings(spec: dict) -> list[bytes]:
    """Bytes of each id."""
    alphabet, vocab = byte_alphabet(), spec["model"]["vocab"]
    special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
    words = [b""] * (max([*vocab.values(), *special.values()]) + 1)
    for word, i in vocab.items():
        words[i] = word.encode() if word in special else bytes(alphabet[c] for c in word)
    for word, i in special.items():
        words[i] = word.encode()
    return words


def joined(words: list[bytes], ids: list[int]) -> str:
    return b"".join(map(words.__getitem__, ids)).decode("utf-8", "replace")


def plain_pieces() -> re.Pattern:
    r"""The pattern of byte-level BPE, `'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+`, for texts up to ``AGREED``.

    No alternative begins with an optional character, so that the first one rules it out.
    """
    known = [chr(c) for c in range(ord(AGREED) + 1)]
    white, letters, numbers = ("".join(re.escape(c) for c in known if regex.match(kind, c)) for kind in (f"[{WHITE}]", r"\p{L}", r"\p{N}"))
    runs = "|".join(f" {kind}+|{kind}+" for kind in (f"[{letters}]", f"[{numbers}]"))
    marks = f"[^{white}{letters}{numbers}]"
    return re.compile(f"{runs}|'(?:s|t|re|ve|m|ll|d)| {marks}+|{marks}+|[{white}]+(?![^{white}])|[{white}]+")


class PairRanks:
    """Rank of pairs of ids for whole arrays: a hash table with linear probing at a tenth of its room."""

    def __init__(self, pairs: np.ndarray, ranks: np.ndarray) -> None:
        """``pairs``: left id << 32 | right id, all different."""
        bits = max(4, int(len(pairs) * 10).bit_length())
        self.shift, self.last = np.uint64(64 - bits), (1 << bits) - 1
        self.pair, self.rank = np.full(1 << bits, -1, np.int64), np.full(1 << bits, -1, np.int32)
        left, at = np.arange(len(pairs)), self._slot(pairs)
        while len(left):
            free = self.pair[at] < 0
            self.pair[at[free]] = pairs[left[free]]  # the last of several that come to one slot has it
            self.rank[at[free]] = ranks[left[free]]
            out = self.pair[at] != pairs[left]
            left, at = left[out], (at[out] + 1) & self.last

    def _slot(self, pairs: np.ndarray) -> np.ndarray:
        return ((pairs.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).view(np.int64)

    def __call__(self, pairs: np.ndarray) -> np.ndarray:
        """Rank of each pair, -1 if it is not merged."""
        at = self._slot(pairs)
        there = self.pair[at]
        out = np.where(there == pairs, self.rank[at], np.int32(-1))
        on = np.flatnonzero((there != pairs) & (there >= 0))
        while len(on):
            at[on] = (at[on] + 1) & self.last
            there = self.pair[at[on]]
            hit = there == pairs[on]
            out[on[hit]] = self.rank[at[on[hit]]]
            on = on[~hit & (there >= 0)]
        return out


class Words:
    """Strings of the ids, and texts of many lists of ids at once."""

    def __init__(self, words: list[bytes]) -> None:
        self.words = words
        self.size = np.array([len(w) for w in words], np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.bytes = np.frombuffer(b"".join(words), np.uint8)

    def _bytes(self, ids: np.ndarray) -> np.ndarray:
        size = self.size[ids]
        to = np.cumsum(size)
        return self.bytes[np.repeat(self.start[ids] - to + size, size) + np.arange(size.sum())]

    def texts(self, ids: np.ndarray, ends: np.ndarray) -> pa.Array:
        """The text of ids[ends[n]:ends[n + 1]] for each n; bytes that are no UTF-8 become U+FFFD."""
        data = np.concatenate([self._bytes(ids[a : a + (1 << 18)]) for a in range(0, max(1, len(ids)), 1 << 18)])
        at = np.concatenate([[0], np.cumsum(self.size[ids])])[ends]
        if at[-1] < 1 << 31:
            out = pa.StringArray.from_buffers(len(ends) - 1, pa.py_buffer(at.astype(np.int32)), pa.py_buffer(data))
            try:
                out.validate(full=True)
                return out
            except pa.ArrowInvalid:
                pass
        return pa.array([data[a:b].tobytes().decode("utf-8", "replace") for a, b in zip(at, at[1:])], pa.string())


class ByteBpe:
    def __init__(self, path: str, memo: int = MEMO) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.alphabet = byte_alphabet()
        vocab = spec["model"]["vocab"]
        special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.special = {k: np.array([v], "<i4").tobytes() for k, v in special.items()}
        self.vocabulary = Words(vocabulary_strings(spec))
        self.words = self.vocabulary.words
        stand_in = {b: c for c, b in self.alphabet.items()}
        self.byte_id = [vocab[stand_in[b]] for b in range(256)]
        self.rank: dict[int, int] = {}
        self.merged: list[int] = []
        for rank, pair in enumerate(spec["model"]["merges"]):
            left, right = pair.split(" ") if isinstance(pair, str) else pair
            self.rank[vocab[left] << 32 | vocab[right]] = rank
            self.merged.append(vocab[left + right])
        ids = self.byte_id
        self.byte_rank = [self.rank.get(ids[a] << 32 | ids[b], -1) for a in range(256) for b in range(256)]
        self.none = len(self.words)
        self.pair_rank, self.merged_ids = PairRanks(np.array(list(self.rank), np.int64), np.array(list(self.rank.values()), np.int32)), np.array(self.merged, np.int64)
        self.byte_ids, self.byte_ranks = np.array(ids, np.int64), np.array(self.byte_rank, np.int32)
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(special, key=len, reverse=True))) + ")") if special else None
        self.coarse = re.compile(f" ?[^{WHITE}]+|[{WHITE}]+(?![^{WHITE}])|[{WHITE}]+").findall
        self.fine, self.odd = plain_pieces().findall, re.compile(f"[^\0-{AGREED}]").search
        bare = spec | {"model": spec["model"] | {"vocab": {}, "merges": []}, "added_tokens": [], "post_processor": None}
        self.library = Tokenizer.from_str(json.dumps(bare)).pre_tokenizer  # the splitter without the vocabulary
        self.memo = Memo(self._value, memo)

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one piece. now[i] is the rank of the pair that begins at symbol i, so an entry that differs from it is stale."""
        n, byte_id, byte_rank = len(piece), self.byte_id, self.byte_rank
        symbol = [byte_id[b] for b in piece]
        now = [byte_rank[a << 8 | b] for a, b in zip(piece, piece[1:])]
        queue = [r << 32 | i for i, r in enumerate(now) if r >= 0]
        if not queue:
            return symbol
        now.append(-1)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        rank, merged, pop, push = self.rank.get, self.merged, heapq.heappop, heapq.heappush
        heapq.heapify(queue)
        while queue:
            entry = pop(queue)
            i = entry & 0xFFFFFFFF
            if now[i] != entry >> 32:
                continue
            s = symbol[i] = merged[entry >> 32]
            j = after[i]
            symbol[j] = now[j] = -1
            k = after[i] = after[j]
            r = -1
            if k < n:
                before[k] = i
                r = rank(s << 32 | symbol[k], -1)
                if r >= 0:
                    push(queue, r << 32 | i)
            now[i] = r
            h = before[i]
            if h >= 0:
                r = now[h] = rank(symbol[h] << 32 | s, -1)
                if r >= 0:
                    push(queue, r << 32 | h)
        return [s for s in symbol if s >= 0]

    def merge_many(self, pieces: list[bytes]) -> list[bytes]:
        """As ``merge`` for each of at most ROWS pieces of at most SHORT bytes, as 32-bit ids.

        Column n of the arrays is piece n, row i its i-th symbol, and a place is i * ROWS + n. ``queue`` holds for every symbol
        rank * SHORT + i of the pair that begins there, so the least of a column is the first entry of that piece's queue.
        """
        size = np.fromiter(map(len, pieces), np.int64, len(pieces))
        n, width = len(pieces), int(size.max())
        read = np.array(pieces, f"S{width}").view(np.uint8).reshape(n, width).T.astype(np.int64)
        row = np.arange(width)[:, None]
        symbol = np.full((width + 2, ROWS), self.none)  # the last row stands for what is before a piece, the one above it for what is after
        symbol[:width, :n] = np.where(row < size, self.byte_ids[read], self.none)
        queue = np.full((width + 2, ROWS), NONE, np.int32)
        rank = self.byte_ranks[read[:-1] << 8 | read[1:]]
        queue[: width - 1, :n] = np.where((rank >= 0) & (row[1:] < size), rank * SHORT + row[:-1], NONE)
        after, before = np.arange(ROWS, (width + 3) * ROWS), np.arange(-ROWS, (width + 1) * ROWS)
        before[:ROWS] += (width + 2) * ROWS
        first, symbol, keys = queue[:width, :n], symbol.reshape(-1), queue.reshape(-1)
        while True:
            entry = first.min(axis=0)
            column = np.flatnonzero(entry != NONE)
            if not len(column):
                break
            entry = entry[column].astype(np.int64)
            i = entry % SHORT * ROWS + column
            s = self.merged_ids[entry // SHORT]
            j, h = after[i], before[i]
            k = after[j]
            symbol[i], symbol[j], keys[j] = s, self.none, NONE
            after[i], before[k] = k, i
            rank = self.pair_rank(np.concatenate([s << 32 | symbol[k], symbol[h] << 32 | s]))
            left = np.concatenate([i, h])
            keys[left] = np.where(rank >= 0, rank * SHORT + left // ROWS, NONE)
        found = symbol.reshape(-1, ROWS)[:width, :n].T
        kept = found != self.none
        ids, ends = found[kept].astype("<i4").tobytes(), (4 * np.cumsum(kept.sum(axis=1))).tolist()
        return [ids[a:b] for a, b in zip([0, *ends], ends)]

    def _ids(self, piece: bytes) -> bytes:
        return array("i", self.merge(piece)).tobytes()

    def _odd(self, part: str) -> list[bytes]:
        """Pieces that the library's splitter makes of a part."""
        return [bytes(self.alphabet[c] for c in p) for p, _ in self.library.pre_tokenize_str(part)]

    def _value(self, part: str) -> bytes:
        if part in self.special:
            return self.special[part]
        return b"".join(map(self._ids, self._odd(part))) if self.odd(part) else self._ids(part.encode())

    def _parts(self, text: str) -> list[str]:
        """Special tokens, pieces, and whole stretches without white space where they hold characters beyond AGREED."""
        if self.cut and "<|" in text:
            return [x for n, p in enumerate(self.cut.split(text)) for x in ([p] if n % 2 else self._between(p))]
        return self._between(text)

    def _between(self, text: str) -> list[str]:
        if not self.odd(text):
            return self.fine(text)
        out: list[str] = []
        for x in self.coarse(text):
            out.append(x) if self.odd(x) else out.extend(self.fine(x))
        return out

    def _merge_new(self, texts: list[list[str]]) -> None:
        """Put into the memo what it lacks, short pieces by arrays; what is left out here is merged when it is asked for."""
        memo, old, special = self.memo, self.memo.old, self.special
        new = [p for p in set(chain.from_iterable(texts)) if p not in memo and p not in old and p not in special]
        if len(new) < FEW:
            return
        if self.odd("".join(new)):
            self._merge_odd([p for p in new if self.odd(p)])
            new = [p for p in new if not self.odd(p)]
        short = [p for p in new if len(p) <= SHORT // 2 or len(p) <= SHORT and p.isascii()]  # no character here has more than two bytes
        short.sort(key=len)
        for at in range(0, len(short), ROWS):
            block = short[at : at + ROWS]
            memo.fill(block, self.merge_many(list(map(str.encode, block))))

    def _merge_odd(self, parts: list[str]) -> None:
        for start in range(0, len(parts), ROWS):
            block = [p for p in parts[start : start + ROWS] if len(p) <= LONG]
            made = [self._odd(p) for p in block]
            short = sorted({b for x in made for b in x if len(b) <= SHORT}, key=len)
            value: dict[bytes, bytes] = {}
            for at in range(0, len(short), ROWS):
                value.update(zip(short[at : at + ROWS], self.merge_many(short[at : at + ROWS])))
            self.memo.fill(block, [b"".join([value[b] if b in value else self._ids(b) for b in x]) for x in made])

    def encode_many(self, texts: list[str]) -> list[bytes]:
        """Ids of each text, 32 bits each."""
        told = [self._parts(t) for t in texts]
        self._merge_new(told)
        return [b"".join(map(self.memo.__getitem__, t)) for t in told]

    def encode(self, text: str) -> np.ndarray:
        return np.frombuffer(self.encode_many([text])[0], "<i4")

    def decode(self, ids: list[int]) -> str:
        return joined(self.words, ids)


@lru_cache(maxsize=2)
def tokenizer(path: str) -> ByteBpe:
    return ByteBpe(path)


@lru_cache(maxsize=2)
def strings(path: str) -> Words:
    """What decoding needs, without the rest of a tokenizer."""
    with open(path, encoding="utf-8") as f:
        return Words(vocabulary_strings(json.load(f)))


def parts(batch: pa.RecordBatch, rows: int = 512, most: int = 1 << 18) -> Iterator[pa.RecordBatch]:
    """A batch in slices of a bounded number of rows and, besides the first row's, of characters in the last column."""
    size = pc.fill_null(pc.binary_length(batch.column(batch.num_columns - 1)), 0).to_numpy(zero_copy_only=False)
    end = np.cumsum(size)
    at = 0
    while at < len(batch):
        held = int(np.searchsorted(end, (end[at - 1] if at else 0) + most, side="right"))
        n = min(max(1, held - at), rows)
        yield batch.slice(at, n)
        at += n


def _encoder(path: str, names: list[str], back: bool):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(path)
        for batch in batches:
            for part in parts(batch):
                coded = bpe.encode_many([x or "" for x in part.column(part.num_columns - 1).to_pylist()])
                ids, ends = np.frombuffer(b"".join(coded), "<i4"), np.cumsum([0, *(len(x) // 4 for x in coded)])
                columns = [*part.columns[:-1], pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(ids, pa.int32()))]
                if back:
                    columns.append(bpe.vocabulary.texts(ids, ends))
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return run


def encode(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text", back: bool = False) -> DataFrame:
    """(doc_id, ids array<int>) of every whole text; with ``back`` also text, what the ids decode to, made by the same worker.

    Special tokens written in a text get their own ids. Null and empty texts have no ids; ids of documents may be
    null or repeat; an empty frame gives an empty one. Other columns are ignored.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    names = ["doc_id", "ids", "text"] if back else ["doc_id", "ids"]
    run = lean(_encoder(path or default_vocabulary(), names, back), tokenizer)
    schema = f"doc_id {kind}, ids array<int>" + (", text string" if back else "")
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, schema)


def _decoder(path: str):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = strings(path)
        for batch in batches:
            for at in range(0, len(batch), 512):
                part = batch.slice(at, 512)
                ids = part.column(1)
                ends = np.cumsum([0, *((x or 0) for x in pc.list_value_length(ids).to_pylist())])
                texts = words.texts(ids.flatten().to_numpy(zero_copy_only=False), ends)
                yield pa.RecordBatch.from_arrays([part.column(0), ids, texts], names=["doc_id", "ids", "text"])

    return run


def decode(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, ids) -> (doc_id, ids, text): vocabulary strings joined; bytes that are no UTF-8 become U+FFFD. Null ids: an empty text."""
    kind = encoded.schema["doc_id"].dataType.simpleString()
    return encoded.select("doc_id", "ids").mapInArrow(_decoder(path or default_vocabulary()), f"doc_id {kind}, ids array<int>, text string")


def digests(decoded: DataFrame) -> DataFrame:
    return decoded.select(
        "doc_id",
        F.size(F.coalesce("ids", F.array().cast("array<int>"))).cast("long").alias("n_tokens"),
        F.sha2(F.coalesce(F.concat_ws(",", F.col("ids").cast("array<string>")), F.lit("")), 256).alias("ids_sha256"),
        F.sha2(F.col("text"), 256).alias("decoded_sha256"),
    )


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(encode(table(spark, sf_dir, "documents", "doc_id", "text"), back=True))
