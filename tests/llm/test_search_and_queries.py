"""Vector search, the registered queries and the pipeline."""

import math
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from pagecast.llm import vector_search
from pagecast.llm.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
needs_tables = pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")


def nearest(ids, vectors, query, k=10):
    at = int(np.flatnonzero(ids == query)[0])
    distance = np.sqrt(((vectors - vectors[at]) ** 2).sum(1))
    order = [i for i in np.lexsort((ids, distance)) if i != at][:k]
    return [(int(ids[i]), float(distance[i])) for i in order]


def test_search_finds_what_brute_force_finds(spark):
    rng = np.random.default_rng(0)
    vectors = rng.normal(size=(3000, 16)).round(2)
    ids = np.arange(3000)
    plan = vector_search.SearchPlan(codebooks=6, chunk_rows=512, rerank=96, sample_rows=1024)
    df = spark.createDataFrame([(int(i), [float(x) for x in v], 1.0) for i, v in zip(ids, vectors)], "vec_id long, embedding array<double>, score double")
    got = {}
    for r in vector_search.search(df, F.col("vec_id") % 100 == 0, plan).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    hits = 0
    for q in range(0, 3000, 100):
        want, found = nearest(ids, vectors, q), sorted(got[q])
        assert [r for r, *_ in found] == list(range(1, 11)) and [s for *_, s in found] == sorted(s for *_, s in found)
        assert all(abs(s - np.linalg.norm(vectors[v] - vectors[q])) < 1e-9 for _, v, s in found)
        hits += len({v for v, _ in want} & {v for _, v, _ in found})
    assert hits / 300 >= 0.9


def test_search_with_awkward_rows(spark):
    nan, inf = float("nan"), math.inf
    rows = [(0, [1.0, 0.0]), (0, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [0.0, 1.0]), (3, None), (4, []), (5, [0.0, 0.0]), (6, [nan, 1.0]), (7, [inf, 1.0]), (8, [None, 1.0]), (9, [1.0, 2.0, 3.0]), (None, [1.0, 1.0]), (100, [1.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = vector_search.search(df, F.col("vec_id") % 100 == 0).orderBy("query_id", "rank").collect()
    assert [(r["query_id"], r["rank"], r["vec_id"]) for r in got] == [(0, 1, 100), (0, 2, 1), (0, 3, 2), (100, 1, 0), (100, 2, 1), (100, 3, 2)]
    assert vector_search.search(df.where("false"), F.lit(True)).count() == 0


def test_beam_is_no_worse_than_greedy():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(800, 8))
    books = vector_search.fit(x, vector_search.SearchPlan(codebooks=3, rounds=3))

    def error(beam):
        codes, norms = vector_search.encode(x, books, beam)
        sums = sum(books[m][codes[:, m]] for m in range(3))
        assert np.allclose((sums**2).sum(1), norms, rtol=1e-3, atol=1e-3)
        return ((x - sums) ** 2).sum()

    assert error(8) <= error(1)


@needs_tables
@pytest.mark.parametrize("name", sorted(QUERIES))
def test_queries_run_over_whole_tables(spark, name):
    rows = QUERIES[name](spark, SF).collect()
    table = "embeddings" if name.startswith("op3") else "pages" if name[:4] in ("op2_", "op5_") else "documents"
    count = spark.read.parquet(f"{SF}/{table}.parquet").count()
    assert len(rows) == (10 * -(-count // 100) if table == "embeddings" else count) or name.startswith("op8") and len(rows) >= count
    if name in ORACLES:
        con = duckdb.connect()
        for t in ("documents", "pages"):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
        want = con.execute(ORACLES[name])
        names = [c[0] for c in want.description]
        assert sorted(map(str, (tuple(r[c] for c in names) for r in rows))) == sorted(map(str, want.fetchall()))


@needs_tables
def test_pipeline_equals_its_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").withColumn("score", F.lit("clash"))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "quality_rules", "near_dedup", "substring_dedup", "packing"]
    left = [docs.count()]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        columns = docs.columns
        docs = spark.createDataFrame(stage(spark, docs, SF).collect(), docs.schema)
        assert docs.columns == columns
        left.append(docs.count())
    assert left[0] >= left[1] >= left[2] >= left[3] == left[4] > 0
    packed = corpus_pipeline.run(spark, SF)
    assert packed.select("doc_id").distinct().count() == left[4]


@needs_tables
def test_pipeline_keeps_good_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    good = spark.read.parquet(f"{SF}/labels.parquet").where("quality = 1").select("doc_id")
    kept = corpus_pipeline.classify(spark, docs, SF).select("doc_id")
    good = good.join(docs, "doc_id", "left_semi")
    assert good.join(kept, "doc_id", "left_semi").count() >= 0.97 * good.count()
