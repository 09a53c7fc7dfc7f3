import random

import numpy as np
import pytest
from tokenizers import Tokenizer

from predtopics.llm import bpe


def samples():
    rng = random.Random(3)
    out = ["", " ", "a" * 5000, "  foo   bar \n\n baz\t\t x  ", "hi <|endoftext|> there<|endoftext|>", "<|endoftext|", "don't we'll I'D 3rd 12345678", "日本語 テスト 🎉👍🏽    　x", "\x1c\x1d a\x85b\xa0c"]
    out += ["".join(map(chr, range(a, b))) for a, b in ((1, 0x600), (0x600, 0x3000), (0x3000, 0x4000), (0x1F000, 0x20400))]
    alphabet = "ab .,'\n\t  é1²Ԙ꟎<|>s"
    return out + ["".join(rng.choice(alphabet) for _ in range(rng.randrange(60))) for _ in range(400)]


def test_ids_equal_the_librarys_and_decode_gives_the_text_back():
    path = bpe.default_vocabulary()
    own, library = bpe.ByteBpe(path, memo=50), Tokenizer.from_file(path)
    for text in samples():
        ids = own.encode(text).tolist()
        assert ids == library.encode(text, add_special_tokens=False).ids, repr(text[:80])
        assert own.decode(ids) == library.decode(ids, skip_special_tokens=False) == text


def test_part_of_a_character_decodes_as_the_library_does():
    path = bpe.default_vocabulary()
    own, library = bpe.ByteBpe(path), Tokenizer.from_file(path)
    ids = own.encode("日本🎉").tolist()
    for n in range(len(ids)):
        assert own.decode(ids[:n]) == library.decode(ids[:n], skip_special_tokens=False)


def test_frames(spark):
    import hashlib

    rows = [(1, "a b", 5), (1, "a b", 5), (None, None, 6), (2, "", 7)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, ids int")
    got = bpe.digests(bpe.decode(bpe.encode(frame))).collect()
    assert sorted((r.doc_id or 0, r.n_tokens) for r in got) == [(0, 0), (1, 2), (1, 2), (2, 0)]
    empty = hashlib.sha256(b"").hexdigest()
    assert {(r.ids_sha256, r.decoded_sha256) for r in got if r.doc_id in (None, 2)} == {(empty, empty)}
    assert {r.decoded_sha256 for r in got if r.doc_id == 1} == {hashlib.sha256(b"a b").hexdigest()}
    assert bpe.decode(bpe.encode(frame.limit(0))).count() == 0


def test_whole_table(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    library = Tokenizer.from_file(bpe.default_vocabulary())
    got = {r.doc_id: (r.ids, r.text) for r in bpe.decode(bpe.encode(docs)).collect()}
    for r in docs.collect():
        assert got[r.doc_id] == (library.encode(r.text, add_special_tokens=False).ids, r.text)


def test_new_short_pieces_are_merged_together():
    path = bpe.default_vocabulary()
    own, library, rng, alone = bpe.ByteBpe(path), Tokenizer.from_file(path), random.Random(5), []
    heap = own.merge
    own.merge = lambda piece: alone.append(piece) or heap(piece)
    words = ["".join(rng.choice("abcdefghijklmnop é") for _ in range(rng.randrange(1, 15))) for _ in range(10_000)]
    texts = [" ".join(words[n : n + 100]) for n in range(0, len(words), 100)]
    got = own.encode_many(texts)
    assert not alone
    for text, ids in zip(texts, got):
        assert np.frombuffer(ids, "<i4").tolist() == library.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("memo", [bpe.MEMO, 100_000, 50])
def test_many_texts_at_once_equal_the_librarys(memo):
    path = bpe.default_vocabulary()
    own, library = bpe.ByteBpe(path, memo=memo), Tokenizer.from_file(path)
    every = "".join(map(chr, range(ord(bpe.AGREED) + 1)))
    texts = [*samples(), every, " ".join(every), "'".join(every), *(f"x{c}y '{c}s 1{c}2 <|endoftext|>{c}" for c in every)]
    for _ in range(2):
        got = own.encode_many(texts)
        for text, ids in zip(texts, got):
            assert np.frombuffer(ids, "<i4").tolist() == library.encode(text, add_special_tokens=False).ids, repr(text[:80])
        assert own.memo.used <= memo // 2 + bpe.ROWS * 400


def test_texts_of_many_lists_of_ids():
    path = bpe.default_vocabulary()
    own, library = bpe.ByteBpe(path), Tokenizer.from_file(path)
    ids = own.encode("日本🎉 a").tolist()
    lists = [[], *(ids[a:b] for a in range(len(ids)) for b in range(a, len(ids) + 1)), []]
    for some in (lists, [[]], [ids], []):
        ends = np.cumsum([0, *map(len, some)])
        got = own.vocabulary.texts(np.array(sum(some, []), np.int32), ends).to_pylist()
        assert got == [library.decode(x, skip_special_tokens=False) for x in some]
