"""The pipeline's stages against brute force, each on its own input, and on odd rows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
import corpus_pipeline
from corpuskit.llm import quality, repetition
from corpuskit.llm.common import stored, table
from corpuskit.llm.word_tokens import load_tokenizer, vocabulary_path
from test_operators import ODD, brute_classes, brute_verdict, weighted_links

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def odd(spark):
    long_ = " ".join(f"the word{i} of it and {i % 7}." for i in range(60))
    rows = [(i, t, "en", "k", len(t or "")) for i, t in enumerate(ODD)] + [(None, long_, "en", None, 0), (None, long_, "en", None, 0), (20, long_ + " End.", None, "k", 1), (20, None, "en", "k", None), (20, long_, "en", "k", 2)]
    return spark.createDataFrame(rows, COLUMNS)


def test_the_stages_are_the_dealt_ones():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "quality_classifier", "near_duplicates", "best_fit_packing"]
    names = __spark_entry__.queries()
    assert "pipeline" in names and sorted(int(n[2:].split("_")[0]) for n in names if n.startswith("op")) == list(range(1, 11))


def key(row):
    return (row.doc_id is not None, row.doc_id or 0, row.text or "")


def check_stages(spark, docs, sf_dir):
    """Run the stages one by one; each is held against plain Python on what its predecessor kept."""
    rules, tok = repetition.RepetitionRules(), load_tokenizer(vocabulary_path("word_bpe_49k.json"))
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = sorted(kept.collect(), key=key)
        model = quality.fit(kept) if name == "quality_classifier" else None
        after_df = stored(stage(spark, kept, sf_dir), name)
        assert after_df.columns == docs.columns
        after = sorted(after_df.collect(), key=key)
        if name == "quality_rules":
            assert after == [r for r in before if brute_verdict(r.text, rules)[1]]
        elif name == "quality_classifier":
            good = {tuple(map(str, (r.doc_id, r.score))): r.kept for r in quality.score_documents(kept, model).collect()}
            assert len(after) == sum(r.kept for r in quality.score_documents(kept, model).collect()) and set(good.values()) <= {True, False}
            assert set(after) <= set(before)
        else:
            classes = brute_classes(len(before), weighted_links([r.text for r in before]) + [(i, j) for i, r in enumerate(before) for j in range(i) if before[j].text == r.text])
            first = {}
            for i, c in enumerate(classes):
                order = (before[i].doc_id is None, before[i].doc_id or 0)
                first[c] = min(first.get(c, order), order)
            assert sorted((r.doc_id is None, r.doc_id or 0) for r in after) == sorted(first.values())
        kept = after_df
    placed = corpus_pipeline.STAGES[-1][1](spark, kept, sf_dir).toPandas()
    tokens = sum(len(tok.encode(r.text, add_special_tokens=False).ids) + 1 for r in kept.collect())
    assert placed.length.sum() == tokens and placed.groupby("sequence_id").length.sum().max(skipna=True) <= 2048 if len(placed) else not tokens
    return kept, placed


def test_pipeline_equals_brute_force(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    kept, placed = check_stages(spark, docs, sf_dir)
    whole = corpus_pipeline.run(spark, sf_dir).toPandas()
    columns = ["doc_id", "piece", "start", "length", "ids_crc32"]
    assert sorted(map(tuple, whole[columns].to_numpy())) == sorted(map(tuple, placed[columns].to_numpy()))
    assert set(placed.doc_id) == {r.doc_id for r in kept.collect()}


def test_pipeline_on_odd_rows(spark, odd, sf_dir):
    kept, placed = check_stages(spark, odd, sf_dir)
    assert kept.filter(F.col("doc_id").isNull() & F.col("text").isNull()).isEmpty()
    assert np.isfinite(placed.length).all()


def test_stages_on_an_empty_table(spark, sf_dir):
    kept = spark.createDataFrame([], COLUMNS)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        kept = stored(stage(spark, kept, sf_dir), "empty")
        assert kept.count() == 0 and kept.columns == [c.split()[0] for c in COLUMNS.split(", ")]
    assert corpus_pipeline.STAGES[-1][1](spark, kept, sf_dir).count() == 0
