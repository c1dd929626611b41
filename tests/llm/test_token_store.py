import io
import zlib

import numpy as np
import public_tokenizers
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from entlink.llm import sstable, token_store as ts

PATH = public_tokenizers.path("byte_bpe_50k.json")
TEXTS = [None, "", " ", "a b", "a  b", " lead", "trail ", "line\nbreak here", "two\n\nbreaks", "\nx", "x\n", "tab\tin side", "don't  we'll 12 3.4%%%",
         "é à ü", "w\x1cq r", "<|endoftext|> x", "日本 語　文", "a " * 3000 + "b", "word " * 30000 + "end", "\r\n x"]


def test_encoder_equals_library():
    t, e = Tokenizer.from_file(PATH), ts.BytePairEncoder(PATH)
    assert e.by_word
    texts = [x or "" for x in TEXTS]
    for got, text in zip(e.encode(texts), texts):
        assert np.frombuffer(got, np.uint32).tolist() == t.encode(text, add_special_tokens=False).ids, text[:40]


def test_encoder_equals_library_on_documents(spark):
    t, e = Tokenizer.from_file(PATH), ts.BytePairEncoder(PATH)
    texts = [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    texts += ["the*** of%%% _a_ a_b ... x's 'tis l'été ²x x² ªº ǅ ﬁ!! don't, a'", "word<|endoftext|> x", "w-<|endoftext|>, y", "<|endoftext|>"]
    for got, text in zip(e.encode(texts), texts):
        assert np.frombuffer(got, np.uint32).tolist() == t.encode(text, add_special_tokens=False).ids, text[:80]


def test_encoder_equals_library_on_mixed_white_space():
    t, e = Tokenizer.from_file(PATH), ts.BytePairEncoder(PATH)
    texts = ["a  b\tc", "a \tb", "a\n\n\nb\tc\td", "a\tb\tc\n\n", " a\xa0b", "a  b\u3000c", "a\x1cb  c", "if x:\n\ty\n\nz", "a\u180eb c"]
    rng = np.random.default_rng(0)
    marks = ["a", "the", "x.", "1", " ", " ", "\n", "\t", "\xa0", "\u3000", "\x1c", "\r"]
    texts += ["".join(rng.choice(marks, int(rng.integers(1, 14)))) for _ in range(5000)]
    for got, text in zip(e.encode(texts), texts):
        assert np.frombuffer(got, np.uint32).tolist() == t.encode(text, add_special_tokens=False).ids, repr(text)


def test_encoder_equals_library_on_all_white_space():
    """White space of every kind, doubled, leading, trailing and next to marks."""
    t, e = Tokenizer.from_file(PATH), ts.BytePairEncoder(PATH)
    spaces = [chr(c) for c in range(0x3001) if chr(c).isspace()] + ["\u200b", "\u2060", "\ufeff"]
    rng = np.random.default_rng(1)
    units = spaces + [" "] * 12 + ["\n"] * 6 + ["a", "the", "price", "10", "EUR", ",", ".", "x's", "é"] * 3
    texts = ["".join(units[i] for i in rng.integers(0, len(units), int(rng.integers(1, 10)))) for _ in range(60_000)] + ["a  b c", "price  10\xa0EUR", ",\x1c,\n\xa0"]
    want = [x.ids for x in t.encode_batch_fast(texts, add_special_tokens=False)]
    for got, text, ids in zip(e.encode(texts), texts, want, strict=True):
        assert np.frombuffer(got, np.uint32).tolist() == ids, repr(text)


def test_rows_of_one_identifier_spread_over_shards(spark):
    docs = spark.createDataFrame([(None if i % 2 else 7, f"text {i}") for i in range(4000)], "doc_id long, text string")
    manifest = ts.write_tokens(docs, lambda: ts.BytePairEncoder(PATH))
    assert manifest.agg(F.max("docs")).first()[0] < 1200
    rows = sorted(ts.read_tokens(manifest).collect(), key=lambda r: r.start)
    assert [r.start for r in rows] == [0, *np.cumsum([r.n_tokens for r in rows])[:-1].tolist()]
    assert [r.id for r in rows] == [None] * 2000 + [7] * 2000


def test_table_round_trip_and_lookup():
    rng = np.random.default_rng(0)
    ids = sorted(rng.integers(-(2**62), 2**62, 3000).tolist()) + [2**62, 2**62]
    rows = [(b"\x00", b"null")] + [(ts.key_of(i), rng.bytes(int(rng.integers(0, 300)))) for i in ids]
    buf = io.BytesIO()
    w = sstable.Writer(buf)
    for k, v in rows:
        w.add(k, v)
    w.close()
    r = sstable.Reader(buf)
    assert list(r) == rows and len(r.blocks) > 3 and r.count == len(rows)
    assert r.get(rows[1500][0]) == [rows[1500][1]]
    assert len(r.get(ts.key_of(2**62))) == 2
    assert not any(r.get(ts.key_of(i + 1)) for i in ids[:500] if i + 1 not in ids)
    assert [ts.id_of(ts.key_of(i)) for i in (None, -5, 0, 7)] == [None, -5, 0, 7]


def test_store_reads_back_all_documents(spark):
    t = Tokenizer.from_file(PATH)
    rows = [(len(TEXTS) - i, x, 1) for i, x in enumerate(TEXTS)] + [(None, "n", 2), (3, "dup", 3), (-4, "neg", 4)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, start int")
    manifest = ts.write_tokens(docs, lambda: ts.BytePairEncoder(PATH), shard_bytes=2000)
    got = sorted(ts.read_tokens(manifest).collect(), key=lambda r: r.start)
    want = [tuple(r) for r in docs.orderBy(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"), "text").collect()]
    at = 0
    for g, (doc_id, text, _) in zip(got, want, strict=True):
        ids = t.encode(text or "", add_special_tokens=False).ids + [0]
        assert (g.id, g.start, g.n_tokens) == (doc_id, at, len(ids))
        assert g.ids_crc32 == zlib.crc32(np.array(ids, "<u4").tobytes())
        at += len(ids)
    uri = [m.uri for m in manifest.collect() if ts.lookup(m.uri, -4)]
    assert len(uri) == 1 and ts.lookup(uri[0], -4) == [t.encode("neg", add_special_tokens=False).ids + [0]]
    empty = ts.write_tokens(docs.where("false"), lambda: ts.BytePairEncoder(PATH))
    assert ts.read_tokens(empty).count() == 0
