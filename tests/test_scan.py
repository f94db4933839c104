"""Scans by matrix products against the expressions that stay in the JVM, on tables with ties, copies and several batches."""

import pytest
from pyspark.sql import functions as F

from aclvec.operators import generators as g
from aclvec.operators import scan as sc
from aclvec.operators import search as se
from aclvec.operators.partitioning import role_homes, role_partition, single_partition
from aclvec.plans.catalog_parts import mod4
from aclvec.plans.catalog_policy import queries_n1
from aclvec.sources.tables import vectors


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture
def small(monkeypatch):
    monkeypatch.setattr(sc, "CHUNK", 16)


@pytest.fixture(scope="module")
def given(spark, sf):
    """Vectors of which every third is a copy of another."""
    v = vectors(spark, sf).select("doc_id", "embedding")
    twin = v.select((F.col("doc_id") + 1).alias("doc_id"), F.col("embedding").alias("twin"))
    v = v.join(twin, "doc_id", "left").select("doc_id", F.when((F.col("doc_id") % 3 == 0) & F.col("twin").isNotNull(), F.col("twin")).otherwise(F.col("embedding")).alias("embedding")).cache()
    return queries_n1(spark, sf), v, g.natural_n1(spark, sf)


def test_nearest_of_all(given, small):
    q, v, _ = given
    assert rows(sc.knn(q, v, 7)) == rows(se.knn(q, v, 7))


def test_nearest_that_are_permitted(given, small):
    q, v, p = given
    mixed = q.withColumn("k", (F.col("query_id") / 20 % 4 + 1).cast("int"))
    assert rows(sc.ground_truth(mixed, v, p)) == rows(se.ground_truth(mixed, v, p))


def test_best_vector_of_a_document_counts(given, small):
    q, v, p = given
    several = v.union(v.select((F.col("doc_id") * 7 % 100).alias("doc_id"), "embedding"))
    assert rows(sc.ground_truth(q, several, p, 5, by_document=True)) == rows(se.top_documents(q, several, p, 5))


@pytest.mark.parametrize("ef", [1, 12, None])
def test_search_at_a_depth(given, small, ef):
    q, v, p = given
    for part in (single_partition(p), role_partition(p), role_homes(p, mod4(p))):
        assert rows(sc.secure_search(q, v, p, part, ef)) == rows(se.secure_search(q, v, p, part, ef))


def test_candidates_and_recall(given, small):
    q, v, p = given
    for part in (single_partition(p), role_partition(p)):
        cols = ["query_id", "rs", "part", "doc_id", F.round("dist", 6)]
        assert rows(sc.candidates(q, v, p, part, 9).select(*cols)) == rows(se.candidates(q, v, p, part, 9).select(*cols))
        truth = se.ground_truth(q, v, p).cache()
        assert rows(sc.recall_by_depth(q, v, p, part, truth, [2, 10, 40])) == rows(se.recall_by_depth(q, v, p, part, truth, [2, 10, 40]))


def test_many_queries_are_asked_in_blocks_and_full_tasks_hand_on(given, small, monkeypatch):
    q, v, p = given
    plain = rows(se.knn(q, v, 3))
    monkeypatch.setattr(se, "MAX_BROADCAST_QUERIES", 3)
    monkeypatch.setattr(se, "MAX_HELD", 5)
    assert rows(sc.knn(q, v, 3)) == plain


@pytest.mark.parametrize("sent", [60, 200_000])
def test_more_queries_than_rows_stay_where_they_are(spark, monkeypatch, sent):
    """Each query many times over, by users of all role sets, ties and copies among few rows; in one block of rows and in several."""
    p = g.hand_h1(spark)
    v = p.docs.selectExpr("doc_id", "array(cast(doc_id % 4 as float), cast(1 as float)) as embedding")
    q = spark.range(300).selectExpr("id as query_id", "id % 6 + 1 as user_id", "4 as k", "array(cast(id % 5 as float), cast(1 as float)) as qvec")
    monkeypatch.setattr(se, "MAX_BROADCAST_QUERIES", 10)
    monkeypatch.setattr(sc, "SENT", sent // 10)
    monkeypatch.setattr(sc, "_scan", lambda *a: pytest.fail("queries sent to every task"))
    for part in (role_partition(p), single_partition(p)):
        assert rows(sc.secure_search(q, v, p, part, k=4)) == rows(se.secure_search(q, v, p, part, k=4))
