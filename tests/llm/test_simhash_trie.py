import numpy as np
import xxhash
from pyspark.sql import types as T

from entlink.llm import simhash_trie as st


def plain_fingerprint(text):
    out, word = [], ""
    folded = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in (text or ""))
    for c in folded + " ":
        if c == " " or "\t" <= c <= "\r":
            if word:
                out.append(word)
            word = ""
        else:
            word += c
    if not out:
        return 0
    shingles = [" ".join(out[i : i + 3]) for i in range(max(1, len(out) - 2))]
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def plain_classes(fps):
    label = list(range(len(fps)))
    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= 3:
                a, b = label[i], label[j]
                label = [min(a, b) if x in (a, b) else x for x in label]
    return label


TEXTS = [None, "", " \t\n", "a", "A", "a b", "a b c", "A  B\nC", "a b c d", "É a é b", "x y z w", "the cat sat on the mat " * 300,
         "the cat sat on the mat " * 300 + "dog", "a b\x1cc d e", "w " * 40000]


def test_fingerprint_matches_plain():
    for t in TEXTS:
        assert st.fingerprint(t) == plain_fingerprint(t)


def test_trie_links_find_all_classes():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 40, dtype=np.uint64)
    keys = [int(b) ^ sum(1 << int(i) for i in rng.choice(64, rng.integers(0, 5), replace=False)) for b in base for _ in range(12)]
    keys = sorted(set(keys))
    links = st.trie_links(np.array(keys, np.uint64), 0)
    for a, b in links:
        assert bin(keys[a] ^ keys[b]).count("1") <= 3
    label = list(range(len(keys)))
    for a, b in links:
        x, y = label[a], label[b]
        label = [min(x, y) if v in (x, y) else v for v in label]
    assert label == plain_classes(keys)


def test_classes_on_fixture(spark):
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**63, 60, dtype=np.uint64)
    fps = sorted({int(b) ^ sum(1 << int(i) for i in rng.choice(64, rng.integers(0, 5), replace=False)) for b in base for _ in range(10)})
    frame = spark.createDataFrame([(int(np.uint64(f).view(np.int64)),) for f in fps], "fp long")
    expect = plain_classes(fps)
    for crowded in (st.CROWDED, 1):
        edges = st.near_links(frame, crowded)
        got = {r.node: r.root for r in st.connected_components(edges).collect()}
        groups = {}
        for f, e in zip(fps, expect):
            s = int(np.uint64(f).view(np.int64))
            groups.setdefault(e, set()).add(got.get(s, s))
        assert all(len(g) == 1 for g in groups.values())
        assert len({next(iter(g)) for g in groups.values()}) == len(groups)


def test_documents_and_edges(spark):
    rows = [(i, t, "x") for i, t in enumerate(TEXTS)] + [(3, "a", "y"), (None, "a", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp string")
    got = st.near_duplicate_classes(docs)
    assert got.columns == ["doc_id", "fp", "component_id"]
    rows = got.collect()
    assert len(rows) == len(TEXTS) + 2
    by = {r.doc_id: r for r in rows if r.doc_id is not None}
    assert by[0].component_id == by[1].component_id == by[2].component_id == 0
    assert by[4].component_id == 3
    empty = spark.createDataFrame([], T.StructType(docs.schema.fields))
    assert st.near_duplicate_classes(empty).count() == 0


def test_components_of_stars_and_paths(spark):
    rng = np.random.default_rng(5)
    rows = [(0, i) for i in range(1, 4000)] + [(10_000 + i, 10_001 + i) for i in range(70)] + [(20_000 + int(a), 20_000 + int(b)) for a, b in rng.integers(0, 300, (200, 2))]
    got = {r.node: r.root for r in st.connected_components(spark.createDataFrame(rows, "u long, v long")).collect()}
    label = {}
    for a, b in rows:
        label.setdefault(a, a), label.setdefault(b, b)
    for _ in range(80):
        for a, b in rows:
            label[a] = label[b] = min(label[a], label[b])
    linked = {x for a, b in rows if a != b for x in (a, b)}
    assert got == {k: v for k, v in label.items() if k in linked}


def test_bit_counts_of_many_rows():
    rng = np.random.default_rng(0)
    for n in (1, 2, 3, 191, 193, 1000, 4097):
        rows = rng.integers(0, 2**63, (n, 2), dtype=np.uint64) * np.uint64(2) + rng.integers(0, 2, (n, 2), dtype=np.uint64)
        bits = np.array([[int(w) >> (63 - b) & 1 for w in r for b in range(64)] for r in rows])
        assert st.bit_counts(rows).tolist() == bits.sum(0).tolist()


def test_links_in_groups_find_all_classes():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2, (30, 512), dtype=np.uint8)
    flat = np.array([b ^ (rng.random(512) < rng.choice([0.0, 0.03, 0.2])) for b in base for _ in range(15)]).astype(np.uint8)
    group = np.arange(len(flat)) % 2
    got = list(range(len(flat)))
    for a, b in st.links_in_groups(group, np.packbits(flat, axis=1), 60):
        assert group[a] == group[b] and (flat[a] ^ flat[b]).sum() <= 60
        got = [min(got[a], got[b]) if x in (got[a], got[b]) else x for x in got]
    want = list(range(len(flat)))
    for a in range(len(flat)):
        for b in range(a):
            if group[a] == group[b] and (flat[a] ^ flat[b]).sum() <= 60:
                want = [min(want[a], want[b]) if x in (want[a], want[b]) else x for x in want]
    assert got == want


def shingles(text, width=5):
    words = text.lower().split()
    return {" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))}


def test_similar_classes_reach_the_similarity(spark):
    """Recall of pairs of a similarity of 0.8 or more, and documents below 0.5 left alone, against all pairs."""
    rng = np.random.default_rng(7)
    rows, sets = [], []
    for i in range(120):
        base = [f"w{x}" for x in rng.integers(0, 4000, int(rng.integers(60, 300)))]
        for j in range(4):
            words = list(base)
            for at in rng.integers(0, len(words), int(len(words) * [0, 0.008, 0.015, 0.2][j])):
                words[at] = f"z{rng.integers(0, 10**6)}"
            rows.append((len(rows), " ".join(words), "x"))
            sets.append(shingles(rows[-1][1]))
    docs = spark.createDataFrame(rows + [(None, rows[0][1], "y"), (900, None, "y"), (901, "", "y"), (902, "one two", "y")], "doc_id long, text string, node string")
    for crowded in (st.CROWDED, 8):
        st_links, keep = st.similar_links, st.similar_links
        st.similar_links = lambda d, s, r: keep(d, s, r, crowded)  # noqa: B023
        try:
            got = {r.doc_id: r.component_id for r in st.similar_classes(docs).collect() if r.doc_id is not None}
        finally:
            st.similar_links = st_links
        wanted = found = 0
        for a in range(len(rows)):
            for b in range(a - a % 4, a):
                s = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
                if s >= 0.8:
                    wanted, found = wanted + 1, found + (got[a] == got[b])
        assert wanted > 200 and found / wanted >= 0.9
        for a in range(len(rows)):
            near = [b for b in range(a - a % 4, a - a % 4 + 4) if b != a and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.5]
            if not near:
                assert got[a] == a
        assert got[900] == got[901] == 900 and got[902] == 902
    assert st.similar_classes(docs.where("false")).count() == 0
