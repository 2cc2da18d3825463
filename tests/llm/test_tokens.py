import io
import random
import zlib

import numpy as np
import pytest

from bundlegraph.llm.bpe import ChunkEncoder, vocabulary
from bundlegraph.llm.token_output import FRAME_IDS, FrameReader, FrameWriter, token_table


def sample_texts():
    import public_tokenizers  # noqa: F401

    rng = random.Random(5)
    alphabet = ["a", "B", "é", "É", "ß", "'s", "'LL", " ", "  ", "\n", "\t", "\x1c", "\x85", " ", " ", "7", "²", "½", ".", "!!", "<|endoftext|>", "<|", "汉", "Σ", "İ", "é", "\U0001f600", "word", " the", "\r\n", "̀", "ǅ", "_"]
    out = ["", None, " ", "\n\n", "The quick  brown\tfox's tail.\n", "x" * 5000, "ab " * 3000]
    return out + ["".join(rng.choice(alphabet) for _ in range(rng.randint(1, 40))) for _ in range(1500)]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_chunks_encode_as_whole_texts_do(name):
    enc = ChunkEncoder(vocabulary(name), room=500)  # small, so that the memory is cleared on the way
    from tokenizers import Tokenizer

    fresh, texts = Tokenizer.from_file(vocabulary(name)), sample_texts()
    texts += ["<|endoftext|>", "a <|startoftext|>b", "no <|ENDOFTEXT|> mark", "x<|endoftext|><|endoftext|> y\n"]
    got = []
    for i in range(0, len(texts), 37):
        got += enc.encode(texts[i : i + 37])
    for t, g in zip(texts, got):
        want = fresh.encode(t or "", add_special_tokens=False).ids
        assert np.frombuffer(g, "<u4").tolist() == want, repr(t)


def test_long_text_is_cut_without_a_change(monkeypatch):
    from bundlegraph.llm import bpe

    enc = ChunkEncoder(vocabulary("byte_bpe_50k.json"))
    text = "some words, and  more\n" * 300 + "é汉 \u3000 ½ word\u0301s" * 200 + "Σ" * 300 + "\n\n" * 50
    whole = enc.encode([text])
    monkeypatch.setattr(bpe, "_LONG", 100)
    assert enc.encode([text, "a b"]) == [whole[0], enc.encode(["a b"])[0]]


class Source(io.BytesIO):
    def size(self):
        return len(self.getvalue())


class Sink(io.BytesIO):
    def close(self):
        self.data = self.getvalue()


def test_frames_round_trip_and_random_access():
    rng = np.random.default_rng(1)
    docs = [(None, b""), (3, b""), *((i, rng.integers(0, 50000, rng.integers(1, 90000)).astype("<u4").tobytes()) for i in range(4, 14))]
    sink = Sink()
    w = FrameWriter(sink)
    for d, ids in docs:
        w.add(d, ids)
    w.close()
    r = FrameReader(Source(sink.data))
    assert [(d, ids) for d, _, ids in r] == docs
    r = FrameReader(Source(sink.data))
    assert r.document(7) == docs[7][1] and r.frames_read <= 2 and len(r.seek) > 2
    assert r.find(9) == [7]
    bad = bytearray(sink.data)
    bad[20] ^= 1
    with pytest.raises(ValueError, match="damaged"):
        list(FrameReader(Source(bytes(bad))))
    import zstandard

    raw = zstandard.ZstdDecompressor().stream_reader(io.BytesIO(sink.data), read_across_frames=True).read()
    assert raw == b"".join(x for _, x in docs)  # a plain reader skips index and seek table
    assert 4 * FRAME_IDS > 0


def test_token_table(spark):
    from tokenizers import Tokenizer

    path = vocabulary("byte_bpe_50k.json")
    rows = [(5, "hello  world<|endoftext|>"), (1, None), (3, ""), (3, "a b"), (None, "x"), (9, "é\n" * 2000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS start")
    got = token_table(df, path).collect()
    t = Tokenizer.from_file(path)
    at, ordered = 0, sorted(got, key=lambda r: r.start)
    assert [r.doc_id for r in ordered] == [None, 1, 3, 3, 5, 9]
    want = sorted((d if d is not None else -1, zlib.crc32(np.array([*t.encode(x or "", add_special_tokens=False).ids, 2], "<u4").tobytes())) for d, x in rows)
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.ids_crc32) for r in got) == want
    for r in ordered:
        assert r.start == at
        at += r.n_tokens
    assert token_table(df.limit(0), path).count() == 0
