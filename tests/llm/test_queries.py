"""The contract queries over whole small tables, against plain versions and SQL."""

import hashlib
import zlib

import duckdb
import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from entlink.llm import queries as q
from entlink.llm.simhash_trie import fingerprint

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def docs(spark):
    return {r.doc_id: r for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


@pytest.mark.parametrize("name", sorted(q.ORACLES))
def test_equals_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = q.QUERIES[name](spark, SF)
    cols = got.columns
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({q.ORACLES[name]})").fetchall()
    key = lambda r: tuple(str(x) for x in r)
    assert sorted(map(tuple, got.collect()), key=key) == sorted(want, key=key)


def test_op1_classes(spark, docs):
    rows = q.op1_simhash_near_dedup(spark, SF).collect()
    fp = {i: fingerprint(r.text) for i, r in docs.items()}
    root = {i: i for i in fp}
    for a in fp:
        for b in fp:
            if a < b and bin(fp[a] ^ fp[b]).count("1") <= 3:
                old, new = max(root[a], root[b]), min(root[a], root[b])
                root = {k: new if v == old else v for k, v in root.items()}
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in rows} == {i: (f"{fp[i]:016x}", root[i]) for i in fp}


def test_op3_positions_and_digests(spark, docs):
    rows = {r.doc_id: r for r in q.op3_token_sstable(spark, SF).collect()}
    t, at = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")), 0
    for i in sorted(docs):
        ids = t.encode(docs[i].text or "", add_special_tokens=False).ids + [0]
        assert (rows[i].start, rows[i].n_tokens, rows[i].ids_crc32) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)


def test_op4_scores_all_documents(spark, docs):
    rows = q.op4_quality_classifier(spark, SF).collect()
    assert sorted(r.doc_id for r in rows) == sorted(docs)
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5)
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    held = [r for r in rows if r.held_out and r.doc_id in labels]
    assert np.mean([r.predicted == labels[r.doc_id] for r in held]) > 0.8


def test_op7_law(spark, docs):
    rows = q.op7_hilbert_sharding(spark, SF).collect()
    assert {r.law for r in rows} == {"rows"} and {r.grown_shard for r in rows} == {None}
    counts = [sum(r.shard == s for r in rows) for s in range(16)]
    assert sum(counts) == len(docs) and max(counts) - min(counts) <= 1
    for s in range(16):
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(counts[s]))
    for r in rows:
        raw = docs[r.doc_id].text.encode()
        assert (r.size, r.text_crc32) == (len(raw) + 1, zlib.crc32(raw))


def test_op8_payloads(spark, docs):
    for r in q.op8_gif_media(spark, SF).collect():
        raw = docs[r.doc_id].text.encode()
        payload = raw + b" " * (-len(raw) % 192 if raw else 192)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
        assert r.media_bytes > 0 and len(r.media_sha256) == 64 and r.feature


def test_op10_marginals(spark, docs):
    rows = q.op10_raking_mix(spark, SF).collect()
    assert len(rows) == len(docs)
    total = sum(r.tokens for r in rows)
    assert sum(r.tokens * r.chance for r in rows) == pytest.approx(total / 2, rel=1e-6)
    tokens, fitted = {}, {}
    for r in rows:
        tokens[r.source] = tokens.get(r.source, 0) + r.tokens
        fitted[r.source] = fitted.get(r.source, 0.0) + r.tokens * r.weight / total
    norm = sum(v**0.5 for v in tokens.values())
    for s, v in tokens.items():
        assert fitted[s] == pytest.approx(v**0.5 / norm, rel=2e-2)
    # What is drawn holds what the chances promise, cell by cell, within one document.
    cells = {}
    for r in rows:
        cells.setdefault((r.source, r.lang, r.topic), []).append(r)
    for own in cells.values():
        expected, drawn = sum(r.chance * r.tokens for r in own), sum(r.tokens for r in own if r.selected)
        assert abs(expected - drawn) <= max(r.tokens for r in own)


def test_only_registered_names_and_columns(spark):
    assert sorted({int(k[2:].split("_")[0]) for k in q.QUERIES}) == list(range(1, 11))
