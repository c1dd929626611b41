import random
import struct

import numpy as np
import public_tokenizers
import sentencepiece

from entlink.llm import piece_transducer as pt

PATH = public_tokenizers.path("piece_bpe_32k.model")
TEXTS = ["", " ", "a", " a", "a ", "  two   blanks    here", "line\nbreak\n\ntwo", "\n", "tab\tx", "don't STOP!! me$$$ 12,345.67", "éàü ñ ß Œ 日本語 テスト 😀 ▁ x▁y",
         "x" * 3000, "ab " * 3000, "́é", "in the internationalization of 的是不了", "\x00\x01 \x7f", " " * 40 + "end"]


def library():
    return sentencepiece.SentencePieceProcessor(model_file=PATH)


def mine():
    with open(PATH, "rb") as f:
        return pt.PieceTransducer(f.read())


def check(sp, t, text):
    got = np.frombuffer(t.encode(text), np.uint32).tolist()
    assert got == sp.encode(text), (text[:60], got[:20], sp.encode(text)[:20])
    if pt.BLANK not in text:
        assert t.decode(t.encode(text)) == text


def test_equals_library():
    sp, t = library(), mine()
    for text in TEXTS:
        check(sp, t, text)
    rng = random.Random(0)
    syllables = ["the", "ing", "ation", "er", "on", " ", " ", "  ", "\n", "é", "日", "Z", "12", "!!", "$$$", "un", "able", "😀", "qu", "x"]
    for _ in range(1500):
        check(sp, t, "".join(rng.choice(syllables) for _ in range(rng.randint(1, 25))))


def test_equals_library_on_documents(spark):
    sp, t = library(), mine()
    for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect():
        check(sp, t, r.text)


def varint(n):
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    return bytes(out) + bytes([n])


def message(*fields):
    out = b""
    for number, value in fields:
        if isinstance(value, float):
            out += varint(number << 3 | 5) + struct.pack("<f", value)
        elif isinstance(value, int):
            out += varint(number << 3) + varint(value)
        else:
            out += varint(number << 3 | 2) + varint(len(value)) + value
    return out


def test_unigram_model_by_tropical_shortest_path():
    words = ["▁", "▁th", "▁the", "e", "t", "h", "he", "re", "r", "▁there", "a", "ab", "b", "ba", "▁ab"]
    rng = random.Random(3)
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3)] + [(w, -rng.random() * 9 - 1, 1) for w in words]
    raw = b"".join(message((1, message((1, p.encode()), (2, s), (3, k)))) for p, s, k in pieces)
    raw += message((2, message((3, 1), (4, len(pieces)))), (3, message((1, b"identity"), (3, 1), (4, 0))))
    sp, t = sentencepiece.SentencePieceProcessor(model_proto=raw), pt.PieceTransducer(raw)
    for _ in range(300):
        text = "".join(rng.choice(["the", "re", "ab", "a", " ", "b", "z", "t"]) for _ in range(rng.randint(1, 12)))
        assert np.frombuffer(t.encode(text), np.uint32).tolist() == sp.encode(text), text


def test_documents_query(spark):
    docs = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (None, "a b", "x"), (2, "é\n", "x")], "doc_id long, text string, ids string")
    rows = pt.encode_documents(docs, PATH).collect()
    assert len(rows) == 4 and all(r.round_trip for r in rows)
    assert pt.encode_documents(docs.where("false"), PATH).count() == 0


def test_time_is_linear_without_blanks():
    import time

    t, took = mine(), {}
    for n in (200_000, 4_000_000):
        text = "abcdefghijklmnopqrstuvwxyz日本語"
        text = (text * (n // len(text) + 1))[:n]
        at = time.perf_counter()
        raw = t.encode(text)
        took[n] = time.perf_counter() - at
        assert t.decode(raw) == text
    assert took[4_000_000] < 80 * took[200_000] and took[4_000_000] < 40


def test_model_that_drops_extra_blanks():
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3)] + [(w, -float(i + 1), 1) for i, w in enumerate(["▁a", "b", "▁", "a", "ab"])]
    raw = b"".join(message((1, message((1, p.encode()), (2, s), (3, k)))) for p, s, k in pieces)
    raw += message((2, message((3, 1), (4, len(pieces)))), (3, message((1, b"identity"), (3, 1), (4, 1))))
    sp, t = sentencepiece.SentencePieceProcessor(model_proto=raw), pt.PieceTransducer(raw)
    for text in ["", "  ", " a  b ", "a   a b", "ab", "   ab  ab"]:
        assert np.frombuffer(t.encode(text), np.uint32).tolist() == sp.encode(text), text


def test_merge_search_settles_few_states():
    """The furthest arc comes first, so states off the path are hardly ever settled; the path is the library's."""
    sp, t = library(), mine()
    chunk = pt.BLANK + "internationalization" * 20
    cost, last = [0.0] + [pt.FAR] * len(chunk), [""] * (len(chunk) + 1)
    t._settle_furthest_first(chunk, cost, last)
    assert sum(c < pt.FAR for c in cost) < len(chunk) / 2
    check(sp, t, chunk[1:])
