"""Exact links inside candidate classes against all pairs."""

import numpy as np
import pytest

from entlink.llm import exact_links as xl
from entlink.llm import simhash_trie as st
from entlink.llm.components import connected_components


def family(rng, copies, size, swapped):
    base = rng.integers(0, 2**62, size, dtype=np.uint64)
    out = []
    for _ in range(copies):
        own = base.copy()
        n = int(rng.integers(0, swapped + 1))
        own[rng.choice(size, n, replace=False)] = rng.integers(0, 2**62, n, dtype=np.uint64)
        out.append(np.unique(own))
    return out


def chain(rng, length, size, step):
    pool = np.sort(rng.integers(0, 2**62, size + length * step, dtype=np.uint64))
    return [np.unique(pool[i * step : i * step + size]) for i in range(length)]


def roots(n, links):
    root = list(range(n))
    for a, b in links:
        low, high = sorted((root[a], root[b]))
        root = [low if r == high else r for r in root]
    return root


def pairs(sets, similarity=0.8, of=None):
    for a in range(len(sets)):
        for b in range(a):
            both = len(np.intersect1d(sets[a], sets[b]))
            if (of is None or of[a] == of[b]) and both / (len(sets[a]) + len(sets[b]) - both) >= similarity:
                yield a, b


@pytest.mark.parametrize("seed", range(4))
def test_spanning_links_join_what_all_pairs_join(seed):
    rng = np.random.default_rng(seed)
    sets = family(rng, 30, 60, 14) + chain(rng, 25, 40, 4) + family(rng, 10, 3, 1) + family(rng, 20, 200, 90)
    sets = [sets[i] for i in rng.permutation(len(sets))]
    made = xl.spanning_links(sets, 0.8)
    assert len(made) < len(sets) and set(map(tuple, map(sorted, made))) <= {tuple(sorted(p)) for p in pairs(sets)}
    assert roots(len(sets), made) == roots(len(sets), pairs(sets))


def test_a_quotient_of_just_the_similarity_is_a_link():
    a = np.arange(9, dtype=np.uint64)
    assert xl.spanning_links([a, a[1:], a[3:]], 8 / 9) == [(0, 1)]
    assert xl.spanning_links([a], 0.8) == [] == xl.spanning_links([], 0.8)


def test_blocks_of_any_size_give_the_same_classes(spark):
    rng = np.random.default_rng(9)
    sets, of = [], []
    for c in range(3):
        own = family(rng, 40, 50, 12) + chain(rng, 20, 40, 4) + family(rng, 8, 50, 40)
        sets += own
        of += [c] * len(own)
    rows = [(c, i, s.tobytes()) for i, (c, s) in enumerate(zip(of, sets))]
    rows += rows[:5] + [(0, 5000, b""), (2, 5001, b"")]
    frame = spark.createDataFrame(rows, "class long, node long, shingles binary")
    want = roots(len(sets), pairs(sets, 0.8, of))
    for block in (xl.BLOCK, 1200):
        got = {r.node: r.root for r in connected_components(xl.exact_links(frame, 0.8, block)).collect()}
        assert [got.get(i, i) for i in range(len(sets))] == want and 5000 not in got, block
    assert xl.exact_links(frame.where("false")).count() == 0


def test_a_repeated_identifier_is_linked_by_any_of_its_texts(spark):
    a, b = np.arange(20, dtype=np.uint64), np.arange(100, 120, dtype=np.uint64)
    rows = [(1, 7, a.tobytes()), (1, 7, b.tobytes()), (1, 8, a.tobytes()), (1, 9, b.tobytes())]
    frame = spark.createDataFrame(rows, "class long, node long, shingles binary")
    for block in (xl.BLOCK, 20):
        got = {r.node: r.root for r in connected_components(xl.exact_links(frame, 0.8, block)).collect()}
        assert got == {7: 7, 8: 7, 9: 7}


def test_no_class_joins_documents_that_similar_pairs_do_not_connect(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = [(r.doc_id, st.shingle_set(r.text)) for r in docs.collect()]
    ids, sets = zip(*[r for r in rows if len(r[1])])
    holders = {}
    for i, s in enumerate(sets):
        for h in s.tolist():
            holders.setdefault(h, []).append(i)
    met = {(a, b) for own in holders.values() for k, a in enumerate(own) for b in own[:k]}
    near = [(a, b) for a, b in met if (n := len(np.intersect1d(sets[a], sets[b]))) / (len(sets[a]) + len(sets[b]) - n) >= 0.8]
    want = dict(zip(ids, roots(len(ids), near)))
    got = {r.doc_id: r.component_id for r in st.similar_classes(docs).collect()}
    assert len(near) > 50
    assert all(want[i] == want[got[i]] for i in ids)
    assert sum(got[ids[a]] == got[ids[b]] for a, b in near) / len(near) >= 0.9
