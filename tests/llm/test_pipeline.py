"""The pipeline's stages, each against plain Python on what it was given."""

from collections import Counter

import corpus_pipeline as cp
from test_contracts import PATTERNS, base_spans, quality_base, shingle_set

from plandistill.llm import queries


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    given = {r.doc_id: r for r in docs.collect()}
    kept = cp.quality_rules(spark, docs, sf)
    assert kept.columns == cp.COLUMNS
    got = {r.doc_id: r.text for r in kept.collect()}
    assert all(not quality_base(t)[-1] for t in got.values()) and len(got) > 0.6 * len(given)
    one = cp.near_duplicates(spark, kept, sf).collect()
    sets = {i: shingle_set(t) for i, t in got.items()}
    left = sorted(r.doc_id for r in one)
    close = lambda a, b: 100 * len(a & b) >= 80 * len(a | b)
    assert not any(close(sets[a], sets[b]) for a in left for b in left if a < b)
    assert all(any(close(sets[i], sets[j]) for j in got if j != i) for i in got if i not in left)
    clean = cp.personal_data(spark, spark.createDataFrame(one, docs.schema), sf)
    for r in clean.collect():
        assert not base_spans(r.text) and r.n_chars == len(r.text)
        assert r.text == got[r.doc_id] or any(f"[{k.upper()}]" in r.text for k in PATTERNS)
    mixed = cp.mix_sources(spark, clean, sf)
    counts = Counter(r.doc_id for r in mixed.collect())
    assert max(counts.values()) <= 3 and set(counts) <= set(left)
    final = cp.encode_pieces(spark, mixed, sf).collect()
    texts = {r.doc_id: r.text for r in clean.collect()}
    assert Counter(r.doc_id for r in final) == counts and all(r.text == texts[r.doc_id] and r.n_pieces == len(r.ids) for r in final)


def test_run_with_extra_columns_and_odd_rows(spark, tmp_path):
    from test_contracts import ODD_TEXTS

    rows = [(i % 15, t, None, "s", len(t or ""), "x", 1) for i, t in enumerate(ODD_TEXTS)] + [(None, ODD_TEXTS[8], "en", None, 1, "y", 2)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, ids string, kept int").write.parquet(f"{tmp_path}/documents.parquet")
    got = cp.run(spark, str(tmp_path)).collect()
    assert any(r.doc_id is None for r in got) and len(got) > 3
    assert queries.op6_pieces(spark, str(tmp_path)).where("not same").count() == 0
