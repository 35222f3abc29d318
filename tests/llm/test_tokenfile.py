import zlib

import numpy as np
import public_tokenizers
import pytest

from rankscan.llm import tokenfile as T

PATH = public_tokenizers.path("byte_bpe_50k.json")
TEXTS = [
    "Plain text, with words.", "", None, "two  spaces", "lines\nof\n\ntext \n here", "\n", " ", " lead", "trail ", "tab\tand\r\nreturn", "nb\xa0space x", "a\u2028b c", "\x1c x", "zero\x00byte x", "<|endoftext|> hi", "é ü ß 漢字 🙂 ok",
    "end. a, b., c.. d.' e' 7. 8, .x ,y é. 漢, _. a_.", "it's we're 12 345 !!! $$$ x", "word " * 30_000, "\u3000 x\u3000y",
]


def ids(text):
    return T.encoder(PATH).tokenizer.encode(text or "", add_special_tokens=False).ids


def test_pieces_give_the_library_ids():
    got = T.Encoder(PATH)([t or "" for t in TEXTS])
    assert [np.frombuffer(x, "<u2").tolist() for x in got] == [ids(t) for t in TEXTS]


@pytest.mark.parametrize("n", [0, 1, 300])
def test_round_trip(spark, n):
    rows = [(1000 - i if i % 50 else None, TEXTS[i % len(TEXTS)], "x") for i in range(n)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, start string").repartition(3)
    got = sorted(map(tuple, T.encode_and_check(df, PATH).collect()), key=lambda r: r[1])
    assert len(got) == n and [r[0] is not None for r in got] == sorted(r[0] is not None for r in got)
    assert [r[0] for r in got if r[0] is not None] == sorted(r[0] for r in rows if r[0] is not None)
    at = 0
    for doc, start, size, crc in got:
        assert start == at
        at += size
    want = sorted((r[0] or -1, len(x := ids(r[1]) + [2]), zlib.crc32(np.array(x, "<u4").tobytes())) for r in rows)
    assert sorted((r[0] or -1, r[2], r[3]) for r in got) == want


def test_sequences_are_of_equal_length_and_views(spark):
    df = spark.createDataFrame([(i, TEXTS[i]) for i in range(len(TEXTS))], "doc_id bigint, text string").coalesce(1)
    manifest = T.write(df, PATH, length=64)
    seqs = T.sequences(spark, manifest).orderBy("shard", "sequence").collect()
    assert {len(r["ids"]) for r in seqs} == {64}
    flat = [x for r in seqs for x in r["ids"][: r["n_real"]]]
    assert flat == [x for t in TEXTS for x in [*ids(t), 2]]
    view, _ = T.Shard(manifest.first()["path"])[0]
    assert not view.flags.owndata and view.dtype == np.uint16


def test_new_pieces_are_encoded_in_rows_and_not_word_by_word(monkeypatch):
    ends = ["", ",", ".\nNext", "'s", "7", "!?", "é", "漢字", "\tx", "ß.", "'", "\n\nz", " b"]
    words = [f"w{chr(97 + i % 26)}{i}{ends[i % len(ends)]}" for i in range(3000)] + ["'ll", "...", "🙂", "\x00", "x\x85y"]
    texts = ["head " + " ".join(words), "other " + " ".join(reversed(words)) + " ", " ".join(words[:7]) + "\n"]
    one, by_word = T.Encoder(PATH), []
    monkeypatch.setattr(T.Encoder, "_word", lambda self, w, f=T.Encoder._word: (by_word.append(w), f(self, w))[1])
    assert [np.frombuffer(x, "<u2").tolist() for x in one(texts)] == [ids(t) for t in texts]
    assert len(by_word) < 20
    other = T.Encoder(PATH)
    other.bytes_of[:] += 1  # a model whose ids do not add up to the bytes: word by word
    assert one(texts) == other(texts) and len(by_word) > 3000
