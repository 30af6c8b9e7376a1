"""The pipeline's stages against what brute force leaves."""

import numpy as np

import corpus_pipeline as cp
from taskmap.llm import bpe, quality
from test_operators import classes, removed_bytes, texts_of


def test_stages(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    columns = docs.columns
    model = quality.trained(spark, docs, tiny)
    hasher = quality.Hasher()
    good = [(i, t) for i, t in texts_of(docs) if model.score(hasher.slots(t.encode())) >= quality.THRESHOLD]
    docs = cp.keep_quality(spark, docs, tiny)
    assert texts_of(docs) == good and docs.columns == columns

    first = {i for i, _, c in classes(good, cp.GRAM, cp.PERCENT) if i == c}
    docs = cp.drop_near_duplicates(spark, docs, tiny)
    kept = [(i, t) for i, t in good if i in first]
    assert texts_of(docs) == kept and docs.columns == columns

    docs = cp.drop_repeated_passages(spark, docs, tiny)
    lost = {i: n for i, _, n, _ in removed_bytes(kept)}
    assert docs.columns == columns and docs.count() == len(kept)
    for i, t in texts_of(docs):
        before = len(dict(kept)[i].encode())
        assert before - lost[i] - 3 * 2 * max(1, lost[i] // 50) <= len(t.encode()) <= before - lost[i]

    docs = cp.mix_sources(spark, docs, tiny)
    assert docs.columns == columns and docs.count() > 0

    out = cp.encode(spark, docs, tiny)
    own = bpe.loaded(bpe.vocabulary_path())
    want = sorted((i, own.encode(t)) for i, t in texts_of(docs))
    assert sorted((r["doc_id"], list(r["ids"])) for r in out.collect()) == want
    assert np.all([r["n_tokens"] == len(r["ids"]) for r in out.collect()])


def test_stages_on_odd_tables(spark, odd, nothing, tiny):
    """Nulls, empty and long texts, repeated rows and ids, further columns with clashing names; an empty table."""
    for name, stage in cp.STAGES:
        out = stage(spark, odd, tiny)
        rows = out.collect()
        if name != cp.STAGES[-1][0]:
            assert out.columns == odd.columns and out.dtypes == odd.dtypes
            assert all((r["batch"], r["size"], r["row"], r["score"]) == (7, "big", "r", 0.5) for r in rows)
        assert rows or name == cp.STAGES[0][0]
        assert not stage(spark, nothing, tiny).collect()


def test_run(spark, tiny):
    assert [name for name, _ in cp.STAGES][0] == "quality classifier" and len(cp.STAGES) == 5
    assert cp.run(spark, tiny).count() > 0


def test_registry():
    import __spark_entry__ as entry

    names = entry.queries()
    assert "pipeline" in names and all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
