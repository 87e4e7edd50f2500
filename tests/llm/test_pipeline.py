"""Each stage of the pipeline against a brute-force version of it, on its own input."""

import re
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tests_llm_shared import brute_components, brute_lines, clip_ids
from treesketch.llm.factorization import fit_quality, score_quality
from treesketch.llm.storage import materialize

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def stages(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    out = [docs]
    for name, stage in corpus_pipeline.STAGES:
        out.append(materialize(stage(spark, out[-1], tiny), "test-stage"))
    return out


def texts(df):
    return {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}


def windows(docs, n=50):
    seen = defaultdict(set)
    for d, t in docs.items():
        w = WORDS.findall((t or "").lower())
        for i in range(len(w) - n + 1):
            seen[tuple(w[i : i + n])].add(d)
    return {k: v for k, v in seen.items() if len(v) > 1}


def test_columns_are_those_of_documents(stages):
    assert all(list(s.columns) == list(stages[0].columns) for s in stages[1:-1])


def test_rejected_documents_go(spark, tiny, stages):
    labels = spark.read.parquet(f"{tiny}/labels.parquet")
    scores = {r.doc_id: r.score for r in score_quality(stages[0], fit_quality(stages[0], labels.select("doc_id", F.col("quality").alias("label")))).collect()}
    assert set(texts(stages[1])) == {d for d, s in scores.items() if s >= 0.7}
    kept, quality = set(texts(stages[1])), {r.doc_id: r.quality for r in labels.collect()}
    assert np.mean([(d in kept) == bool(q) for d, q in quality.items()]) > 0.95


def test_lines_of_ten_documents_go(stages):
    want = {d: t for d, _, _, t in brute_lines(list(texts(stages[1]).items()), 10)}
    assert texts(stages[2]) == want
    assert all(r.n_chars == len(r.text) for r in stages[2].collect())


def test_one_document_of_each_group_stays(stages):
    docs = texts(stages[2])
    parents = brute_components(sorted(docs.items()))
    assert texts(stages[3]) == {d: t for d, t in docs.items() if parents[d] == d}


def test_no_long_passage_is_left_twice(stages):
    before, after = texts(stages[3]), texts(stages[4])
    assert set(before) == set(after) and not windows(after)
    shared = {d for docs in windows(before).values() for d in docs}
    untouched = [d for d in before if d not in shared]
    assert np.mean([before[d] == after[d] for d in untouched]) > 0.98  # the rest are fuzzy repeats
    for docs in windows(before).values():
        assert before[min(docs)] == after[min(docs)] or min(docs) in shared


def test_every_token_is_packed_once(stages):
    docs = texts(stages[4])
    by_doc, bins = defaultdict(list), defaultdict(list)
    for r in stages[5].collect():
        by_doc[r.doc_id].append((r.piece, r.start, r.length))
        bins[r.sequence_id].append((r.offset, r.length))
    assert {d: sum(p[2] for p in ps) for d, ps in by_doc.items()} == {d: len(clip_ids(t)) + 1 for d, t in docs.items()}
    for places in bins.values():
        ends = [a + b for a, b in sorted(places)]
        assert [a for a, _ in sorted(places)] == [0, *ends[:-1]] and ends[-1] <= 4096
    total = sum(p[2] for ps in by_doc.values() for p in ps)
    assert len(bins) <= 1.02 * -(-total // 4096) + 1


def test_odd_documents_pass_through(spark, tiny):
    rows = [(None, None, None, None, None), (1, "", "en", "s", 0), (2, None, "en", "s", 0), (None, "text without an id " * 20, "en", "s", 5), (3, "same text here and there again", "en", "s", 1), (3, "same text here and there again", "en", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES[1:]:
        docs = materialize(stage(spark, docs, tiny), "test-odd")
    assert sorted(str(r.doc_id) for r in docs.collect()) == ["1", "2", "3", "None", "None"]
    empty = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES:
        empty = materialize(stage(spark, empty, tiny), "test-empty")
    assert empty.count() == 0
