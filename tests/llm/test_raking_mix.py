import numpy as np
import pytest

from entlink.llm import raking_mix as m


def plain_rake(cells, goals, sweeps=200):
    total = sum(cells.values())
    w = {k: v / total for k, v in cells.items()}
    for _ in range(sweeps):
        for axis, goal in enumerate(goals):
            for value, g in goal.items():
                s = sum(v for k, v in w.items() if k[axis] == value)
                for k in w:
                    if k[axis] == value and s:
                        w[k] *= g / s
    return w


def test_rake_meets_marginals_and_plain_version(spark):
    rng = np.random.default_rng(0)
    cells = {(f"s{a}", f"l{b}", str(c)): int(rng.integers(1, 1000)) for a in range(5) for b in range(3) for c in range(4) if rng.random() < 0.9}
    df = spark.createDataFrame([(*k, v) for k, v in cells.items()], "source string, lang string, topic string, tokens long")
    targets = {"source": {f"s{a}": a + 1.0 for a in range(5)}, "lang": {"l0": 2.0, "l1": 1.0, "l2": 1.0}, "topic": None}
    got = {(r.source, r.lang, r.topic): r.share for r in m.rake(df, targets).collect()}
    topic = {c: sum(v for k, v in cells.items() if k[2] == c) ** 0.5 for c in "0123"}
    goals = [{k: v / 15 for k, v in targets["source"].items()}, {k: v / 4 for k, v in targets["lang"].items()}, {c: v / sum(topic.values()) for c, v in topic.items()}]
    want = plain_rake(cells, goals)
    assert all(abs(got[k] - want[k]) < 1e-5 for k in cells)
    for axis, goal in enumerate(goals):
        for value, g in goal.items():
            assert sum(v for k, v in got.items() if k[axis] == value) == pytest.approx(g, abs=1e-5)


def test_chances_meet_budget(spark):
    df = spark.createDataFrame([("a", "x", "0", 10, 0.6), ("b", "x", "0", 1000, 0.3), ("c", "x", "0", 500, 0.1)], "source string, lang string, topic string, tokens long, share double")
    got = {r.source: r.chance for r in m.chances(df, 0.4).collect()}
    assert got["a"] == 1.0
    assert 10 + got["b"] * 1000 + got["c"] * 500 == pytest.approx(0.4 * 1510)
    assert got["b"] * 1000 / (got["c"] * 500) == pytest.approx(3)


def test_mixture_edges(spark):
    rows = [(i, None if i % 50 == 0 else "word lexical " * (i % 9) + f"item{i}", ["en", "fr", None][i % 3], f"s{i % 4}" if i % 11 else None, 1.0) for i in range(400)]
    rows += [(None, "null id", "en", "s0", 1.0), (3, rows[3][1], "fr", "s3", 1.0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, chance double")
    out = m.mixture(docs, budget=0.5).collect()
    assert len(out) == len(rows) and all(0 <= r.chance <= 1 for r in out)
    assert sum(r.chance * r.tokens for r in out) == pytest.approx(0.5 * sum(r.tokens for r in out), rel=1e-6)
    kept = m.sampled(docs, budget=0.5)
    assert kept.columns == docs.columns
    assert sorted(str(r.doc_id) for r in kept.collect()) == sorted(str(r.doc_id) for r in out if r.selected)
    assert m.mixture(docs.where("false")).count() == 0
    assert m.sampled(docs.where("false")).count() == 0


def test_word_vectors():
    assert m.word_vector(None)[0] == 0 and not m.word_vector("")[1].any()
    n, v = m.word_vector("b a A b b b a a")
    assert n == 8 and sorted(v[v > 0]) == [707, 707]


def test_topics_are_clusters_of_words(spark):
    rng = np.random.default_rng(4)
    words = [[f"t{t}w{i}" for i in range(40)] for t in range(4)]
    rows = [(i, " ".join(rng.choice(words[i % 4], 60)), "en", "s") for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    got = {r.id: r.topic for r in m.described(docs.repartition(5)).collect()}
    assert got == {r.id: r.topic for r in m.described(docs.coalesce(1)).collect()}
    # Every cluster holds one field of words: eight clusters over four fields.
    fields = {}
    for i, t in got.items():
        fields.setdefault(t, set()).add(i % 4)
    assert all(len(f) == 1 for f in fields.values()) and len(fields) >= 4


def test_draws_are_even_and_whole(spark):
    """Realised tokens of each cell are within its longest document of the expected ones, and draws follow the chances."""
    rng = np.random.default_rng(9)
    rows = [(i, " ".join(["w"] * int(rng.integers(1, 200)) + [f"x{i}"]), ["en", "fr"][i % 2], f"s{i % 5}") for i in range(3000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    out = m.mixture(docs, budget=0.3).collect()
    cells = {}
    for r in out:
        cells.setdefault((r.source, r.lang, r.topic), []).append(r)
    for own in cells.values():
        expected, drawn = sum(r.chance * r.tokens for r in own), sum(r.tokens for r in own if r.selected)
        assert abs(expected - drawn) <= max(r.tokens for r in own) + 1
        assert abs(sum(r.selected for r in own) - sum(r.chance for r in own)) <= 1
    whole = sum(r.tokens for r in out if r.selected)
    for s in range(5):
        share = sum(r.tokens for r in out if r.selected and r.source == f"s{s}") / whole
        assert share == pytest.approx(sum(r.chance * r.tokens for r in out if r.source == f"s{s}") / sum(r.chance * r.tokens for r in out), rel=0.05)


def test_null_is_a_category_apart(spark):
    docs = spark.createDataFrame([(i, f"word {i}", "en", [None, "", "a"][i % 3]) for i in range(300)], "doc_id long, text string, lang string, source string")
    out = m.mixture(docs, 0.4, {"source": {None: 0.5, "": 0.25, "a": 0.25}}).collect()
    tokens = {s: sum(r.tokens * r.chance for r in out if r.source == s) for s in (None, "", "a")}
    assert tokens[None] / sum(tokens.values()) == pytest.approx(0.5, abs=1e-3) and tokens[""] / sum(tokens.values()) == pytest.approx(0.25, abs=1e-3)


def test_rake_goes_on_until_the_marginals_hold(spark):
    # Sources almost tied to one language: slow to converge.
    rows = [("a", "x", "0", 100), ("a", "y", "0", 100), ("b", "y", "0", 100)]
    df = spark.createDataFrame(rows, "source string, lang string, topic string, tokens long")
    got = m.rake(df, {"source": {"a": 0.8, "b": 0.2}, "lang": {"x": 0.79, "y": 0.21}}).collect()
    assert sum(r.share for r in got if r.source == "a") == pytest.approx(0.8, rel=1e-5)
    assert sum(r.share for r in got if r.lang == "x") == pytest.approx(0.79, rel=1e-5)


def test_rake_reports_targets_that_cannot_hold(spark):
    df = spark.createDataFrame([("a", "x", "0", 10), ("b", "y", "0", 10)], "source string, lang string, topic string, tokens long")
    with pytest.warns(m.RakingWarning):
        m.rake(df, {"source": {"a": 0.8, "b": 0.2}, "lang": {"x": 0.79, "y": 0.21}}).collect()


def test_drawn_tokens_hold_the_targets(spark):
    # The cell (a, x) cannot give what raking asks of it; other cells of source a and of language x can.
    cells = {("a", "x", "0"): 100, ("a", "y", "0"): 400, ("b", "x", "0"): 400, ("b", "y", "0"): 1100}
    rows = [(i, *k, v) for i, (k, v) in enumerate(cells.items())]
    known = spark.createDataFrame(rows, "id long, source string, lang string, topic string, tokens long")
    targets = {"source": {"a": 0.5, "b": 0.5}, "lang": {"x": 0.5, "y": 0.5}, "topic": {"0": 1.0}}
    got = {(r.source, r.lang, r.topic): r.chance for r in m.cell_chances(known, 0.4, targets).collect()}
    drawn = {k: got[k] * v for k, v in cells.items()}
    total = sum(drawn.values())
    assert total == pytest.approx(0.4 * sum(cells.values())) and max(got.values()) == pytest.approx(1.0)
    for axis, d in enumerate(m.DIMS):
        for value, goal in targets[d].items():
            assert sum(v for k, v in drawn.items() if k[axis] == value) / total == pytest.approx(goal, abs=1e-3)
    with pytest.warns(m.RakingWarning):
        m.cell_chances(known, 0.9, targets).count()
