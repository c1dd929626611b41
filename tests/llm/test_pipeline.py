import random

import pytest

pipeline = pytest.importorskip("corpus_pipeline")

from entlink.llm import quality_ftrl, raking_mix, simhash_trie  # noqa: E402


def fixture(spark, path):
    rng = random.Random(1)
    vocab = ["alpha", "bravo", "charlie", "delta", "echo", "foxtrot", "golf", "hotel", "india"]
    rows, labels = [], []
    for i in range(240):
        words = [rng.choice(vocab) + str(rng.randint(0, 30)) for _ in range(60)]
        good = i % 4 > 0
        rows.append((i, " ".join(words if good else [w.upper() + "!!" for w in words]), ["en", "fr"][i % 2], f"s{i % 3}", None))
        labels.append((i, int(good), 0))
    rows += [(1000 + i, rows[i][1], "en", "s0", None) for i in range(0, 60, 3)]
    rows += [(2000 + i, rows[i][1] + " " + rows[i][1].split()[-1], "en", "s0", None) for i in range(1, 240, 20)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return spark.read.parquet(f"{path}/documents.parquet")


def test_stages_against_plain_versions(spark, tmp_path):
    docs = fixture(spark, tmp_path)
    assert [n for n, _ in pipeline.STAGES] == ["quality", "exact_dedup", "near_dedup", "mixing", "sentencepiece"]
    now = docs.collect()
    weights = quality_ftrl.fit(docs, spark.read.parquet(f"{tmp_path}/labels.parquet"))
    frame = docs
    for name, stage in pipeline.STAGES:
        out = stage(spark, frame, str(tmp_path))
        if name == "quality":
            want = [r for r in now if quality_ftrl.score(weights, quality_ftrl.features(r.text)) >= 0.5]
            assert 0 < len(want) < len(now)
        elif name == "exact_dedup":
            best = {}
            for r in now:
                best[r.text.lower()] = min(best.get(r.text.lower(), r.doc_id), r.doc_id)
            want = [r for r in now if r.doc_id == best[r.text.lower()]]
        elif name == "near_dedup":
            fp = {r.doc_id: int.from_bytes(simhash_trie.wide_fingerprint(r.text), "big") for r in now}
            root = {i: i for i in fp}
            for a in sorted(fp):
                for b in sorted(fp):
                    # Here similar pairs are near copies and all others are far from the budget.
                    if a < b and (fp[a] ^ fp[b]).bit_count() <= 88:
                        old, new = max(root[a], root[b]), min(root[a], root[b])
                        root = {k: new if v == old else v for k, v in root.items()}
            want = [r for r in now if root[r.doc_id] == r.doc_id]
        elif name == "mixing":
            drawn = {r.doc_id for r in raking_mix.mixture(frame, pipeline.TOKEN_SHARE).collect() if r.selected}
            want = [r for r in now if r.doc_id in drawn]
            assert 0.6 < len(want) / len(now) <= 1
        else:
            got = out.collect()
            assert sorted(r.doc_id for r in got) == sorted(r.doc_id for r in now) and all(r.round_trip for r in got)
            continue
        assert out.columns == docs.columns
        assert sorted(out.collect()) == sorted(want), name
        now, frame = want, spark.createDataFrame(want, docs.schema)


def test_empty_tables(spark, tmp_path):
    docs = fixture(spark, tmp_path).where("false")
    for name, stage in pipeline.STAGES:
        assert stage(spark, docs, str(tmp_path)).count() == 0, name
