import zlib

import numpy as np

from entlink.llm import quality_ftrl as q

GOOD = ["the cat sat on the mat", "a dog ran to the park and back", "we read the book by the sea"]
BAD = ["THE!! CAT!! SAT!!", "of%%% the&&& to### a$$$", "spam spam spam spam spam spam"]


def test_features_edges():
    for t in (None, "", " \n"):
        idx, val = q.features(t)
        assert idx.tolist() == [0] and len(val) == 1
    idx, val = q.features("word " * 50000)
    assert np.isfinite(val).all()


def test_learns_and_scores_all_rows(spark):
    rows = [(i, (GOOD if i % 2 else BAD)[i // 2 % 3] + f" w{i}", "x") for i in range(200)]
    rows += [(1000, None, "x"), (1001, "", "x"), (None, "the cat", "x"), (5, rows[5][1], "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)] + [(None, 1), (1000, None)], "doc_id long, quality int")
    w = q.fit(docs, labels)
    out = q.scored(docs, w).collect()
    assert len(out) == len(rows)
    held = [r for r in out if r.doc_id is not None and r.doc_id < 200 and zlib.crc32(str(r.doc_id).encode()) % 3 == 1]
    assert np.mean([(r.score >= 0.5) == bool(r.doc_id % 2) for r in held]) > 0.95
    assert all(0 <= r.score <= 1 for r in out)
    none = q.fit(docs, labels.where("false"))
    assert {r.score for r in q.scored(docs, none).collect()} == {0.5}
    assert q.scored(docs.where("false"), w).count() == 0
    assert q.with_score(docs, w, score_col="p").count() == len(rows)


def test_held_out_rows_do_not_train(spark):
    docs = spark.createDataFrame([(i, GOOD[i % 3], "x") for i in range(60)], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, quality int")
    turned = spark.createDataFrame([(i, 1 - i % 2 if zlib.crc32(str(i).encode()) % 3 == 1 else i % 2) for i in range(60)], "doc_id long, quality int")
    assert np.array_equal(q.fit(docs, labels), q.fit(docs, turned))


def plain_ftrl(rows, alpha=0.5, beta=1.0, l1=1e-4, l2=1e-3, epochs=3):
    """The updates one coordinate at a time, in dictionaries."""
    import math

    z, n = {}, {}

    def weight(i):
        s = z.get(i, 0.0)
        return 0.0 if abs(s) <= l1 else -(s - math.copysign(l1, s)) / ((beta + math.sqrt(n.get(i, 0.0))) / alpha + l2)

    for _ in range(epochs):
        for x, label in rows:
            w = {i: weight(i) for i, _ in x}
            p = 1 / (1 + math.exp(-max(-35.0, min(35.0, sum(w[i] * v for i, v in x)))))
            for i, v in x:
                g = (p - label) * v
                step = (math.sqrt(n.get(i, 0.0) + g * g) - math.sqrt(n.get(i, 0.0))) / alpha
                z[i] = z.get(i, 0.0) + g - step * w[i]
                n[i] = n.get(i, 0.0) + g * g
    return {i: weight(i) for i in z}


def test_training_equals_plain_updates():
    rng = np.random.default_rng(2)
    words = ["alpha", "beta", "gamma", "delta", "EPS", "12", "!!"]
    texts = [" ".join(rng.choice(words, int(rng.integers(1, 12)))) for _ in range(80)]
    rows = [(q.features(t), float("alpha" in t)) for t in texts]
    # A coordinate that stands twice in a row of features (the bias with a hashed feature) would be one update here and two there.
    rows = [(f, y) for f, y in rows if len(set(f[0].tolist())) == len(f[0])]
    got = q.train(rows)
    want = plain_ftrl([(list(zip(i.tolist(), v.tolist())), y) for (i, v), y in rows])
    assert len(rows) > 60 and np.count_nonzero(got) == sum(w != 0 for w in want.values())
    assert all(abs(got[i] - w) < 1e-5 for i, w in want.items())
