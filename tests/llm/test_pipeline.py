"""The pipeline's stages, each on the rows that its predecessor kept."""

from collections import defaultdict

import pytest
from conftest import SF

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, kept = docs.columns, []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, SF).write.parquet(str(tmp_path / str(k)))
        docs = spark.read.parquet(str(tmp_path / str(k)))
        kept.append(docs.collect())
        if k < len(corpus_pipeline.STAGES) - 1:
            assert docs.columns == columns, name
    rules, lines, near, mixed, packed = kept
    assert all(len(r.text.split()) >= 50 for r in rules)
    assert {r.doc_id for r in near} <= {r.doc_id for r in lines} <= {r.doc_id for r in rules}
    assert {r.doc_id for r in mixed} <= {r.doc_id for r in near} and max(sum(r.doc_id == x.doc_id for x in mixed) for r in mixed[:20]) <= 2
    by = defaultdict(int)
    for r in packed:
        by[r.sequence_id] += r.length
    assert max(by.values()) <= 2048 and {r.doc_id for r in packed} == {r.doc_id for r in mixed}


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0


def test_stages_of_an_empty_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, SF).count() == 0


def test_stages_keep_columns_of_any_name(spark):
    names = "whole bad_id bad_key row_key near_key mix_size mix_note mix_key mix_turn tpl_note tpl_key tpl_drop tpl_dropped tpl_lines s".split()
    prose = " ".join(f"a{i}" for i in range(120))
    line = "a line that stands in many of the documents again and again, word by word"
    rows = [(i, f"{prose} z{i}\n{line}" if i % 3 else f"{prose} " + " ".join(f"y{i}q{k}" for k in range(120)), "en", "a") for i in range(12)]
    rows += [(None, prose, None, None), (20, None, "en", "a"), (21, "", None, "b"), (22, " ".join(f"v{i}" for i in range(60_000)), "fr", None), (1, rows[1][1], "en", "a")]
    docs = spark.createDataFrame([(*r, len(r[1] or ""), *[f"own {c}" for c in names]) for r in rows], "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{c} string" for c in names))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        got = out.collect()
        assert got and all(r[c] == f"own {c}" for r in got for c in names), name
        # a stage gives rows it got, but for lines that go
        known = {(r.doc_id, r.lang, r.source) for r in docs.collect()}
        assert {(r.doc_id, r.lang, r.source) for r in got} <= known, name
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() > 0
    kept = corpus_pipeline.quality_rules(spark, docs, SF).collect()
    assert {r.doc_id for r in kept} == {*range(12), None, 22} and len(kept) == 15
    near = corpus_pipeline.near_duplicates(spark, docs, SF).collect()
    assert sum(r.doc_id in (1, 2, 4, 5, 7, 8, 10, 11) for r in near) == 2  # the first one, in its two rows
    assert {0, 3, 6, 9, None, 20, 21, 22} <= {r.doc_id for r in near}
