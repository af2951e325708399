"""The registered queries and the pipeline on the smallest tables."""

import os

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from patternspark.llm import queries, simhash


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in ("documents", "pages", "labels"):
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("key", sorted(queries.oracle_sql()))
def test_sql(spark, sf, duck, key):
    got, want = queries.queries()[key](spark, sf).toPandas(), duck.execute(queries.oracle_sql()[key]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    plain = lambda d: sorted(map(repr, d[cols].astype(object).where(d[cols].notna(), None).itertuples(index=False, name=None)))
    assert plain(got) == plain(want)


def test_language_held_out_accuracy(spark, sf):
    docs = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = [r for r in queries.op4_language(spark, sf).collect() if r.held_out]
    assert np.mean([r.lang_pred == docs[r.doc_id] for r in got]) > 0.97


def test_html_articles_of_the_given_pages(spark, sf):
    import html
    import re

    pages = {r.page_id: r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    for r in queries.op10_html(spark, sf).collect():
        inner = re.search(r"<article>(.*)</article>", pages[r.page_id], re.S)[1]
        plain = re.sub(r"</?[a-z0-9]+[^>]*>", lambda m: "" if m[0] in ("<b>", "</b>") else " ", inner)
        assert r.text == " ".join(html.unescape(plain).split())


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    quality = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality", "language", "exact_dedup", "near_dedup", "packing"]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id: r.text for r in docs.collect()}
        out = corpus_pipeline.cut(stage(spark, docs, sf), "test")
        assert out.columns == docs.columns
        after = {r.doc_id: r.text for r in out.collect()}
        assert set(after) <= set(before) and all(before[k] == v for k, v in after.items())
        gone = set(before) - set(after)
        if name == "quality":
            good = [k for k in before if quality.get(k) == 1]
            assert sum(k in after for k in good) >= 0.98 * len(good) and any(quality.get(k) == 0 for k in gone)
        if name == "exact_dedup":
            assert len({simhash.ascii_lower_py(t) for t in before.values()}) == len(after)
        if name == "near_dedup":
            sets = {k: simhash.shingle_set(t) for k, t in before.items()}
            assert all(any(simhash.jaccard(sets[k], sets[o]) >= 0.8 for o in sets if o < k) for k in gone)
            up = {k: k for k in sets}  # the same by brute force: of all that pairs connect, the least id stays

            def top(k):
                while up[k] != k:
                    k = up[k]
                return k

            for a in sets:
                for b in sets:
                    if a < b and simhash.jaccard(sets[a], sets[b]) >= 0.8:
                        up[max(top(a), top(b))] = min(top(a), top(b))
            assert set(after) == {top(k) for k in sets}
        docs = out
    packed = corpus_pipeline.pack(spark, docs, sf).toPandas()
    assert set(packed["doc_id"]) == {r.doc_id for r in docs.collect()}
    assert packed.groupby("sequence_id")["length"].sum().max() <= 1024
    empty = docs.limit(0)
    assert corpus_pipeline.language(spark, empty, sf).count() == 0 and corpus_pipeline.near(spark, empty, sf).count() == 0
    assert corpus_pipeline.pack(spark, empty, sf).count() == 0


def test_stages_keep_columns_of_any_name(spark, sf):
    """Columns that clash with what the operators add, nulls, empty texts, repeated rows."""
    from pyspark.sql import functions as F

    clash = ["score", "selected", "sample_key", "log_weight", "lang_pred", "_text", "_gone", "_keep", "text_", "c0", "in0", "id", "norm", "kept", "a.b"]
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 60")
    docs = docs.union(docs.where("doc_id < 3")).union(docs.where("doc_id = 5").withColumn("doc_id", F.lit(1000).cast("long")).withColumn("text", F.lit(None).cast("string")))
    docs = docs.union(docs.where("doc_id = 5").withColumn("doc_id", F.lit(1001).cast("long")).withColumn("text", F.lit("")))
    docs = docs.select("*", *[F.lit(f"own {c}").alias(c) for c in clash])
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        rows = out.collect()
        assert rows and all(r[c] == f"own {c}" for r in rows for c in clash), name


def test_registered():
    import __spark_entry__ as entry

    keys = entry.queries()
    assert "pipeline" in keys and all(any(k.startswith(f"op{n}_") for k in keys) for n in range(1, 11))
    assert os.path.exists(corpus_pipeline.__file__)
