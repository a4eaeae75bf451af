"""The corpus pipeline against its stages by brute force."""

from __future__ import annotations

import hashlib

import sentencepiece
from pyspark.sql import functions as F

from attrgraph.llm.queries import PIECE_MODEL

DATA = "/root/testdata/sf0.001"


def test_pipeline_stages(spark):
    import corpus_pipeline

    from tests.llm.test_operators import brute_components, brute_contamination, brute_secrets

    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    columns = docs.columns
    (_, good), (_, unique), (_, cut), (_, redact), (_, encode) = corpus_pipeline.STAGES
    kept = good(spark, docs, DATA)
    assert kept.columns == columns
    labels = spark.read.parquet(f"{DATA}/labels.parquet")
    gone = docs.join(kept.select("doc_id"), "doc_id", "left_anti").join(labels, "doc_id")
    assert gone.where("quality = 1").count() <= 0.05 * labels.where("quality = 1").count()
    rows = {r.doc_id: r.text for r in kept.collect()}
    expected = {i for i, (_, root) in brute_components(rows).items() if root == i}
    single = unique(spark, kept, DATA)
    assert single.columns == columns and {r.doc_id for r in single.collect()} == expected
    clean = cut(spark, single, DATA)
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect()]
    after = [(r.doc_id, r.text) for r in clean.collect()]
    assert clean.columns == columns and len(after) == len(expected)
    assert not any(h for _, h, _ in brute_contamination(after, items))
    before = [(r.doc_id, r.text) for r in single.collect()]
    hit = {d[0] for d, (_, h, _) in zip(before, brute_contamination(before, items), strict=True) if h}
    assert {d for d, t in after if t != rows[d]} == hit
    safe = redact(spark, clean, DATA)
    assert safe.columns == columns and not safe.where("n_chars != length(text)").count()
    for r in safe.collect():
        assert not brute_secrets(r.text)
    out = encode(spark, safe, DATA)
    model = sentencepiece.SentencePieceProcessor(model_file=PIECE_MODEL)
    text = {r.doc_id: r.text for r in safe.collect()}
    for r in out.collect():
        ids = model.encode(text[r.doc_id])
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
    whole = {r.doc_id: r.ids_sha256 for r in corpus_pipeline.run(spark, DATA).collect()}
    assert whole == {r.doc_id: r.ids_sha256 for r in out.collect()}


def test_pipeline_on_odd_rows(spark):
    import corpus_pipeline

    rows = [(1, None, None, None, None), (None, "some text of no note here", "en", "s", 25), (2, "", None, None, 0), (3, "same words in this one text", "en", "s", 1), (4, "same words in this one text", "en", "s", 1), (4, "same words in this one text", "en", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for frame in (docs, docs.limit(0)):
        out = frame
        for _, stage in corpus_pipeline.STAGES[1:]:
            out = stage(spark, out, DATA)
        ids = [r.doc_id for r in out.orderBy(F.col("doc_id")).collect()]
        assert ids == ([None, 1, 2, 3] if frame is docs else [])


def test_a_stage_drops_what_another_kept_in_the_worker():
    from attrgraph.session import kept, lean

    kept("pieces")["model"], kept("quality")["memo"] = 1, 2
    assert list(lean(lambda batches: (b + 1 for b in batches), "quality")(iter([1, 2]))) == [2, 3]
    assert not kept("pieces") and kept("quality").pop("memo") == 2
