import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
from tokenizers import Tokenizer

from filekind.llm import token_binary as tb


def test_round_trip_of_any_ids():
    rng = random.Random(1)
    for n in (0, 1, 127, 128, 129, 1000, 5000):
        for top in (1, 2, 12, 16, 33, 60, 64):
            ids = np.array([rng.getrandbits(rng.randint(1, top)) for _ in range(n)], np.uint64)
            words, offsets, escapes = tb.pack(ids)
            assert (tb.unpack(words, offsets, escapes.astype(np.int64), n) == ids).all()


def test_words_are_packed():
    words, _, _ = tb.pack(np.ones(1280, np.uint64))
    assert len(words) == 30  # 60 + 60 + 8 ids in each block
    assert len(tb.pack(np.full(1280, 40_000, np.uint64))[0]) == 430


def want(rows):
    t, start, out = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), 0, []
    for d, text in rows:
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 2], "<u4")
        out.append((d, start, len(ids), zlib.crc32(ids.tobytes())))
        start += len(ids)
    return out


def test_whole_table(spark, sf):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()]
    assert sorted(map(tuple, tb.op8_simple8b_tokens(spark, sf).collect())) == want(rows)


def test_edges(spark, tmp_path):
    rows = [(7, "Don't STOP we're 12 <|endoftext|> ok"), (3, None), (5, ""), (-2, " \t"), (9, "x" * 30_000), (8, "é café  ΣΑΣ \x85 end"), (11, "中文 字　字")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'clash' payload", "1 part")
    path = public_tokenizers.path("word_bpe_49k.json")
    folder = f"file://{tmp_path}/a"
    segments = tb.write_segments(df, path, folder)
    assert sorted(map(tuple, tb.read_documents(segments, folder).collect())) == want(sorted(rows))
    names = {r.file for r in segments.collect()}
    assert names == {f.name for f in (tmp_path / "a").iterdir()}
    back = {d: i for f in names for d, i in zip(*(lambda x: (x[0], np.split(x[2], np.cumsum(x[1])[:-1])))(tb.read_segment((tmp_path / "a" / f).read_bytes())))}
    assert sorted(back) == sorted(d for d, _ in rows) and back[5].tolist() == [2]
    assert tb.read_documents(tb.write_segments(df.limit(0), path, f"{folder}b"), f"{folder}b").count() == 0
    nulls = spark.createDataFrame([(None, "b"), (1, "a"), (1, "a")], "doc_id long, text string")
    assert [r.doc_id for r in tb.read_documents(tb.write_segments(nulls, path, f"{folder}c"), f"{folder}c").orderBy("start").collect()] == [None, 1, 1]


def test_ids_are_the_librarys_for_any_text(monkeypatch):
    rng = random.Random(5)
    path = public_tokenizers.path("word_bpe_49k.json")
    library, words = Tokenizer.from_file(path), tb.Words(path)
    parts = [
        "a", "B", "z", "don't", "'S", "'", "1", "23", ",", ".", "!!", "#", "_", "-", " ", "  ", "\t", "\n", "\x0b", "\x0c", "\x1c", "\x85", "\u00a0", "\u2028", "\u3000", "<|", "|>", "<|endoftext|>", "<|ENDOFTEXT|>", "<|StartOfText|>",
        "<|startoftext|>", "endoftext", "é", "É", "ß", "ÿ", "Ÿ", "Œ", "İ", "ı", "Ⱥ", "Ⱦ", "ⱥ", "Σ", "ς", "Å", "K", "\u0301", "\u0331", "\u030c", "H\u0331", "J\u030c", "T\u0308", "ǰ", "ẖ", "中", "文", "가", "ᄀ", "ᅡ", "ﬁ", "٣", "²", "½", "😀", "\u200d", "\u200b", "\x00", "\x1a", "&amp;", "$", "%",
    ]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 12))) for _ in range(12_000)] + ["aȺ1", "_Ⱦ'.Z", "<|ENDOFTEXT|>", "H\u0331."]
    for most in (400_000, 50):
        monkeypatch.setattr(tb, "MOST_WORDS", most)
        for at in range(0, len(texts), 1500):
            some = texts[at : at + 1500]
            ids, lengths = words.encode(pa.array(some, pa.string()))
            for t, got in zip(some, np.split(ids, np.cumsum(lengths)[:-1]), strict=True):
                assert got.tolist() == library.encode(t, add_special_tokens=False).ids, t


def test_words_of_letters_go_together_and_keep_their_ids():
    """Many words of letters go to the library in one text; odd ones beside them go alone, and every text keeps the ids of its own encoding."""
    path = public_tokenizers.path("word_bpe_49k.json")
    plain, words, calls = Tokenizer.from_file(path), tb.Words(path), []
    rng = random.Random(5)
    made = ["".join(rng.choice("abcdeghilmnorstuwzäßéÑÈ") for _ in range(rng.randint(1, 14))) for _ in range(500)]
    odd = ["l'eau", "éte", "x1y", "</w>", "a</w>b", "<|endoftext|>", "Ω", "क़", "가", "\x01", "日本", " ", "a b", "don't", "...", "İ", "ﬁn"]
    texts = ["", *(" ".join(rng.choice(made + odd) for _ in range(rng.randint(1, 80))) for _ in range(60)), " ".join(odd)]

    class Counted:
        def __getattr__(self, name):
            return getattr(plain, name)

        def encode_batch_fast(self, pieces, **how):
            calls.append(len(pieces))
            return plain.encode_batch_fast(pieces, **how)

    words.tokenizer = Counted()
    ids, lengths = words.encode(pa.array(texts))
    want = [e.ids for e in plain.encode_batch(texts, add_special_tokens=False)]
    assert lengths.tolist() == list(map(len, want)) and ids.tolist() == [i for w in want for i in w]
    assert sum(calls) < 100
    words.closes[:] = False  # a vocabulary that marks no ends
    again = ["new " + t for t in texts]
    ids, _ = words.encode(pa.array(again))
    assert ids.tolist() == [i for e in plain.encode_batch(again, add_special_tokens=False) for i in e.ids]
