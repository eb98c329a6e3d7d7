"""Queries against DuckDB on the smallest tables."""

import duckdb
import pytest
from latentseg import queries, relops  # noqa: F401

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", [
    "lines", "snippets", "chunk_frequencies", "bytes_with_prefix_space", "vocab_base_topk", "vocab_seed", "path_counts", "segmentations", "em_round1_expected", "em_round2_theta", "corpus_loglik_r2", "model_theta", "unseen_tokens",
    "init_by_frequency", "best_score_chunks", "marginal_chunks", "segmentation_chunks", "predict_documents", "posterior_documents", "margin_documents", "prior_snippets", "label_subset_predict", "marginal_predict", "high_entropy_group",
    "predict_capped", "thresholds", "thresholds_shared", "predict_guarded", "predict_guarded_documents", "ngram_lm_addk", "ngram_lm_interp", "ngram_lm_backoff", "ngram_margins", "fixed_seg_nb", "accuracy_by_corruption", "macro_metrics",
    "composition_cube", "events_sessions", "events_shuffle_hash", "sketch_distinct", "sketch_top_sources", "sketch_percentiles",
])
def test_equal(spark, sf, con, name):
    df = queries.queries()[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)
    rel = con.sql(queries.oracle_sql()[name])
    assert sorted(rel.columns) == cols
    want = sorted(rel.select(*[duckdb.ColumnExpression(c) for c in cols]).fetchall(), key=repr)
    assert got == want
