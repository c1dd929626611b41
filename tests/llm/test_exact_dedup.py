import hashlib

import pytest

from entlink.llm import exact_dedup as x

ROWS = [(1, "Same Text", "a"), (2, "same text", "b"), (3, None, "c"), (4, "", "d"), (5, "É", "e"), (6, "é", "f"), (7, "SAME TEXT", "g"), (8, "w " * 200000, "h"),
        (9, "W " * 200000, "i"), (None, "same text", "j"), (2, "same text", "k"), (None, "alone", "l")]


def fold(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


@pytest.mark.parametrize("keep", ["smallest", "largest"])
def test_decisions_and_survivors(spark, keep):
    hot = [(i, "HOT copy" if i % 2 else "hot copy", "z") for i in range(100, 1500)]
    docs = spark.createDataFrame(ROWS + hot, "doc_id long, text string, kept string")
    got = x.decisions(docs, keep=keep).collect()
    groups = {}
    for i, t, _ in ROWS + hot:
        groups.setdefault(fold(t), []).append(i)
    best = {k: (min if keep == "smallest" else max)([i for i in v if i is not None], default=None) for k, v in groups.items()}
    assert len(got) == len(ROWS) + len(hot)
    by_hash = {hashlib.sha256(k.encode()).hexdigest(): k for k in groups}
    for r in got:
        k = by_hash[r.text_sha256]
        assert r.keep_id == best[k] and r.group_size == len(groups[k])
        assert not r.kept or r.doc_id == best[k]
    assert sum(r.kept for r in got) == len(groups)
    left = x.survivors(docs, keep=keep)
    assert left.columns == docs.columns
    assert sorted(str(r.doc_id) for r in left.collect()) == sorted(str(b) for b in best.values())


def test_empty(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert x.decisions(docs).count() == 0 and x.survivors(docs).count() == 0
