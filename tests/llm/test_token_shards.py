import zlib

import numpy as np
from tokenizers import Tokenizer

from predtopics.llm import token_shards as ts


def expected(rows):
    """Plain rendering: (doc_id, start, n_tokens, crc) in key order, nulls first, texts in order within a key."""
    library = Tokenizer.from_file(ts.default_vocabulary())
    start, out = 0, []
    for key, text in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or "")):
        ids = library.encode(text or "", add_special_tokens=False).ids + [1]
        out.append((key, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    return out


def test_parts_between_white_space_give_the_librarys_ids():
    coder, library = ts.LibraryIds(ts.default_vocabulary(), None, memo=50), Tokenizer.from_file(ts.default_vocabulary())
    texts = ["", " ", "It's  DON'T\n\x0b\x1c a\xa0b\x85c　d", "ΣΑΣ ΑΣ. İstanbul ﬁ Å Å e ́x", '"1" <|endoftext|>x <|startoftext|> <|endoftext|>', "日本語 🎉👍🏽"]
    texts += ["".join(map(chr, range(a, a + 0x300))) for a in range(1, 0xD000, 0x300)]
    for text in texts:
        assert np.frombuffer(coder.encode(text), f"<u{coder.width}").tolist() == library.encode(text, add_special_tokens=False).ids, repr(text[:60])


def test_words_go_to_the_librarys_model_alone():
    coder, library = ts.LibraryIds(ts.default_vocabulary(), None), Tokenizer.from_file(ts.default_vocabulary())
    rng = np.random.default_rng(8)
    letters = [chr(c) for c in range(0x41, 0x100) if c not in (0xD7, 0xF7) and chr(c).isalpha() and chr(c) not in "ªºµ"]
    words = ["".join(rng.choice(letters, n)) for n in rng.integers(1, 90, 2000)]
    words += [w + "".join(rng.choice(list("!\"#%&()*+,-./:;<=>?@[]^_`{|}~"), 3)) for w in words[:500]]
    odd = ["\u212a\u212b", "e\u0301t", "caf\xe9\u0301,", "\xe9=\u0338", "n\xf7m", "\xaa\xba\xb5", "l'\xe9t\xe9", "\xdf\xc3", "3\xe8me", "\u0130i", "\xe9's"]
    ids = {t: library.encode(t, add_special_tokens=False).ids for t in [*words, *odd, "<| " + " ".join(words), "x" * 5000]}

    class Counted:
        seen: list = []

        def encode(self, text, **how):
            self.seen.append(text)
            return library.encode(text, **how)

    coder.library = Counted()
    for text in [*words, "x" * 5000]:
        assert np.frombuffer(coder.encode(text), "<u2").tolist() == ids[text], repr(text[:60])
    assert not [t for t in Counted.seen if any(c.isalpha() for c in t)]  # marks alone go the whole way
    for text in [*odd, "<| " + " ".join(words)]:
        assert np.frombuffer(coder.encode(text), "<u2").tolist() == ids[text], repr(text[:60])


def test_a_tokenizer_with_other_steps_goes_the_whole_way(tmp_path):
    from tokenizers import normalizers

    library = Tokenizer.from_file(ts.default_vocabulary())
    library.normalizer = normalizers.Sequence([library.normalizer, normalizers.Replace("a", "o")])
    library.save(str(tmp_path / "other.json"))
    coder = ts.LibraryIds(str(tmp_path / "other.json"), None)
    for text in ("banana", "\xe9tat, \xe0 Anna"):
        assert np.frombuffer(coder.encode(text), "<u2").tolist() == library.encode(text, add_special_tokens=False).ids


def test_perfect_hash_is_minimal_and_knows_its_keys():
    rng = np.random.default_rng(2)
    for n in (0, 1, 2, 63, 64, 65, 5000):
        keys = rng.permutation(10 * n)[:n].astype(np.int64)
        values = ts.hashed(keys, np.zeros(n, np.int64))
        index = ts.PerfectHash.build(values)
        assert sorted(index.slots(values).tolist()) == list(range(n))


def test_round_trip_whole_table(spark, sf_dir, tmp_path):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = ts.write_shards(docs, str(tmp_path / "shards"), shard_ids=5000)
    got = sorted((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in ts.read_all(spark, out).collect())
    assert got == sorted(expected([(r.doc_id, r.text) for r in docs.collect()]))
    by_key = {r.doc_id: r.ids for r in ts.read_all(spark, out).collect()}
    wanted = [0, 7, 199, 10_000, -3]
    found = {r.key: bytes(r.ids) for r in ts.lookup(spark, out, spark.createDataFrame([(k,) for k in wanted], "key long")).collect()}
    assert found == {k: bytes(by_key[k]) for k in wanted if k in by_key}


def test_nulls_repeats_and_empty(spark, tmp_path):
    rows = [(5, "b \" c", 1), (5, "a", 2), (5, "a", 3), (None, "x \" y", 4), (None, None, 5), (-2, "", 6), (9, None, 7)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, seq int")
    for most in (1, 3, 1000):
        out = ts.write_shards(frame, str(tmp_path / f"s{most}"), shard_ids=most)
        got = sorted(((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in ts.read_all(spark, out).collect()), key=lambda r: r[1])
        assert got == expected([r[:2] for r in rows])
    out = ts.write_shards(frame.limit(0), str(tmp_path / "none"))
    assert ts.read_all(spark, out).count() == 0
