"""The pipeline's stages, each on what the one before kept, against plain re-computation on a small fixture."""

import random

from pyspark.sql import functions as F

import corpus_pipeline
from gridmul.llm import op5_quality
from gridmul.llm.common import table
from test_operators import brute_lines, brute_links

SF = "/root/testdata/sf0.001"


def test_stages_take_effect(spark):
    docs = table(spark, SF, "documents")
    kept = corpus_pipeline.quality_rules(spark, docs, SF)
    assert kept.columns == docs.columns
    verdict = {r.doc_id: r.kept for r in op5_quality.quality(docs).collect()}
    assert sorted(r.doc_id for r in kept.select("doc_id").collect()) == sorted(k for k, v in verdict.items() if v)
    lines = corpus_pipeline.line_dedup(spark, kept, SF)
    before = sorted((r.doc_id, r.text) for r in kept.collect())
    after = {k: t for (k, _), t in zip(before, brute_lines(before, 50)) if t.strip()}
    got = {r.doc_id: r for r in lines.collect()}
    assert {k: r.text for k, r in got.items()} == after and all(r.n_chars == len(r.text) for r in got.values())
    near = corpus_pipeline.ngram_jaccard_join(spark, lines, SF)
    rows = sorted(after.items())
    assert sorted(r.doc_id for r in near.select("doc_id").collect()) == sorted({c for _, c, _ in brute_links(rows)})
    mixed = corpus_pipeline.source_mixing(spark, near, SF)
    assert mixed.columns == docs.columns and mixed.select("doc_id").distinct().count() >= 0.85 * near.count()
    last = corpus_pipeline.sentencepiece(spark, mixed, SF)
    assert last.count() == mixed.count() and last.where("NOT decoded_equal").count() == 0


def test_clashing_columns(spark):
    rng = random.Random(2)
    text = " ".join(str(rng.randrange(10_000)) for _ in range(120))
    names = ["_gm_id", "_gm_rate", "_gm_copies", "_gm_copy", "_gm_removed", "_gm_lines", "_gm_uid", "_gm_ranges", "class_id", "kept", "uid", "rate"]
    df = spark.createDataFrame([(k, t, "en", "s", 9, *range(len(names))) for k, t in ((1, text), (2, text + "\n" + text), (3, None))], "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{n} int" for n in names))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, df, SF)
        assert out.columns == df.columns and all(r["_gm_uid"] == 6 and r["rate"] == 11 for r in out.collect())
    assert corpus_pipeline.sentencepiece(spark, df, SF).count() == 3


def test_repeated_rows_and_nulls(spark):
    rng = random.Random(1)
    text = " ".join(str(rng.randrange(10_000)) for _ in range(120))
    other = " ".join(str(rng.randrange(10_000)) for _ in range(120))
    df = spark.createDataFrame([(1, text, "en", "s", 5, "x"), (1, text, "en", "s", 5, "x"), (2, text, "en", "s", 5, "x"), (3, other, None, None, None, "y"), (None, None, None, None, None, None)], "doc_id long, text string, lang string, source string, n_chars long, rate string")
    near = corpus_pipeline.ngram_jaccard_join(spark, df, SF)
    assert near.columns == df.columns
    assert sorted(str(r.doc_id) for r in near.collect()) == ["1", "3", "None"]
    for stage in (corpus_pipeline.quality_rules, corpus_pipeline.line_dedup, corpus_pipeline.source_mixing):
        out = stage(spark, df, SF)
        assert out.columns == df.columns
        out.count()
        assert stage(spark, df.where(F.lit(False)), SF).count() == 0
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "line_dedup", "ngram_jaccard_join", "source_mixing", "sentencepiece"]
