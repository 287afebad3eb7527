"""Registered queries against their DuckDB texts, and the pipeline against its parts."""

from __future__ import annotations

import re
from collections import Counter

import pytest

import corpus_pipeline
from nodeflux.llm import registry
from tests.compare import assert_same


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_query_equals_oracle(spark, sf, name):
    assert_same(registry.QUERIES[name](spark, sf), registry.ORACLES[name], sf)


def test_pipeline_stages(spark, sf):
    from tests.llm.test_corpus_ops import brute_components
    from tests.llm.test_text_ops import brute_leaks, brute_lines

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = docs.columns
    items = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()]
    for name, stage in corpus_pipeline.STAGES:
        before = {r.doc_id: r.text for r in docs.collect()}
        docs = corpus_pipeline.cut(stage(spark, docs, sf), f"test-{name}")
        if name == "best_fit_packing":
            assert {r.doc_id for r in docs.collect()} == set(before)
            break
        assert docs.columns == names
        after = {r.doc_id: r.text for r in docs.collect()}
        if name == "quality_classifier":
            assert all(before[d] == t for d, t in after.items())
            labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
            right = [(d in after) == bool(q) for d, q in labels.items() if d in before]
            assert sum(right) / len(right) > 0.95
        elif name == "line_dedup":
            assert Counter((d, t) for d, t in after.items()) == Counter((d, t) for d, _, _, t in brute_lines(list(before.items())))
            assert all(r.n_chars == len(r.text) for r in docs.collect())
        elif name == "ngram_jaccard_join":
            assert set(after) == {d for d, c in brute_components(list(before.items()), 5, 80).items() if d == c}
        else:
            assert set(after) == {d for d, *_, bad in brute_leaks(list(before.items()), items) if not bad}


def test_nothing_else_imports_the_package():
    import pathlib

    root = pathlib.Path(corpus_pipeline.__file__).parent / "nodeflux"
    for path in root.rglob("*.py"):
        if "llm" not in path.parts:
            assert not re.search(r"nodeflux\.llm|from \.+llm", path.read_text())


def test_stages_take_odd_rows(spark, sf):
    """Nulls in every column, empty and very long texts, repeated rows, an empty table, columns that clash with inner names."""
    from pyspark.sql import functions as F

    from nodeflux.llm import jaccard

    names = corpus_pipeline.STAGES
    plain = spark.read.parquet(f"{sf}/documents.parquet")
    good = plain.orderBy(F.desc(F.length("text"))).first().text
    rows = [(1, good), (1, good), (2, good + " end"), (3, None), (4, ""), (None, good), (None, None), (5, "é " * 40_000), (6, "a line that is shared by all\n1"),
            (7, "a line that is shared by all\n2"), (8, "a line that is shared by all\n3"), (1, "an unrelated text under a known id, of ten words or so")]
    docs = spark.createDataFrame([(d, t, None, None, None, 1, "x", 2.0) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long, id int, th string, score double")
    for table in (docs, docs.limit(0)):
        for name, stage in names:
            got = stage(spark, table, sf)
            kept = got.collect()
            if name == "best_fit_packing":
                assert (len(kept) >= len(rows)) if table is docs else not kept
                continue
            assert got.columns == docs.columns and len(kept) <= table.count()
            if table is not docs:
                assert not kept
            elif name == "line_dedup":
                assert len(kept) == len(rows) and all(r.n_chars == len(r.text) and r.th == "x" for r in kept)
                assert {r.doc_id: r.text for r in kept if r.doc_id in (6, 7, 8)} == {6: "1", 7: "2", 8: "a line that is shared by all\n3"}
            elif name == "ngram_jaccard_join":
                want = [(1, good), (3, None), (4, ""), (None, good), (None, None), *rows[7:]]
                least = {r.doc_id for r in jaccard.jaccard_components(docs, 5, 80).collect() if r.doc_id == r.component_id}
                assert 2 not in least and Counter((r.doc_id, r.text) for r in kept) == Counter(x for x in want if x[0] is None or x[0] in least or x[1] == rows[-1][1])
            elif name == "benchmark_decontamination":
                assert {r.text for r in kept} >= {None, ""} and all(r.score == 2.0 for r in kept)
