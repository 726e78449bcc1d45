"""Stages of the pipeline on a small table: each against what its operator says."""

import random

import corpus_pipeline as C
from quiesce.llm import exact_dedup, simhash

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def prose(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(["the", "rain", "stone", "river", "walk", "lamp", "green", "over"]) + r.choice(["", "ing", "s", "ed"]) for _ in range(n))


def test_stages(spark, tmp_path):
    good = [prose(120, s) for s in range(60)]
    texts = good + [good[0]] * 3 + [good[1] + " tail"] + [" | ".join(prose(60, s).upper().split()) + " ###" for s in range(40)] + ["write to jo@x.org " + prose(50, 99)]
    docs = spark.createDataFrame([(i, t, "en", f"s{i % 4}", len(t)) for i, t in enumerate(texts)], DOCS)
    bad = set(range(64, 104))
    spark.createDataFrame([(i, int(i not in bad), 0) for i in range(len(texts))], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    now = docs
    seen = {}
    for name, stage in C.STAGES:
        out = stage(spark, now, str(tmp_path))
        out.write.parquet(str(tmp_path / name))
        before, now = now, spark.read.parquet(str(tmp_path / name))
        seen[name] = (before, now)
        if name != "packing":
            assert now.columns == docs.columns
    ids = {n: {r.doc_id for r in b.collect()} for n, (_, b) in seen.items()}
    assert ids["quality"] == set(range(len(texts))) - bad
    assert ids["exact"] == {r.doc_id for r in exact_dedup.exact_dedup(seen["quality"][1]).filter("kept").collect()} and not ids["exact"] & {60, 61, 62}
    assert ids["near"] == {r.component_id for r in simhash.near_duplicates(seen["exact"][1], **C.NEAR).collect()}
    assert ids["personal"] == ids["near"]
    last = {r.doc_id: r for r in seen["personal"][1].collect()}
    assert last[104].text.startswith("write to [EMAIL] ") and last[104].n_chars == len(last[104].text) and last[5].text == texts[5]
    assert ids["packing"] == ids["personal"]
    assert C.run(spark, str(tmp_path)).select("doc_id").distinct().count() == len(ids["packing"])


def test_stages_lose_no_text(spark, tmp_path):
    """Repeated and null ids, null and empty texts, ties and clashing names, against a plain count of texts."""
    rows = [(0, "b"), (1, "a"), (1, "b"), (1, "a"), (None, "c"), (None, "c"), (None, "d"), (2, None), (3, ""), (4, " "), (5, prose(3000, 5))]
    docs = spark.createDataFrame([(i, t, "en", "s", 9) for i, t in rows], DOCS).selectExpr("*", "'x' as row", "'x' as score", "'x' as t", "'x' as k", "'x' as keep_id")
    docs.write.parquet(str(tmp_path / "in"))
    docs = spark.read.parquet(str(tmp_path / "in"))
    kept = C.exact(spark, docs, "").collect()
    norm = lambda t: " ".join((t or "").split(" "))
    assert sorted(norm(r.text) if (r.text or "").strip() else r.text or "" for r in kept) == sorted({norm(t) if (t or "").strip() else t or "" for _, t in rows})
    assert {(r.doc_id, r.text) for r in kept if r.text in ("a", "b")} == {(1, "a"), (0, "b")} and all(r.row == r.score == "x" for r in kept)
    left = C.near(spark, docs, "")
    assert left.columns == docs.columns and {r.text for r in left.collect()} >= {"a", "b", "c", "d"} and left.filter("text = 'a'").count() == 1
    clean = C.personal(spark, docs, "")
    assert clean.columns == docs.columns and clean.count() == len(rows) and clean.filter("text is null").first().n_chars == 9
    spark.createDataFrame([(1, 1, 0), (2, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    good = C.quality(spark, docs, str(tmp_path))
    assert good.columns == docs.columns
    assert C.packing(spark, docs, "").select("doc_id", "piece").count() >= len(rows)
    for name, stage in C.STAGES:
        assert stage(spark, docs.limit(0), str(tmp_path)).count() == 0, name
