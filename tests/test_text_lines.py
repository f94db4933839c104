"""Vectors of lines read as bytes, and places in several partitionings from one scan, against the plain ways."""

import pytest
from pyspark.sql import functions as F

from aclvec.operators import generators as g
from aclvec.operators import scan as sc
from aclvec.operators import search as se
from aclvec.operators.partitioning import role_homes, role_partition, single_partition
from aclvec.plans import catalog_search as cs
from aclvec.plans import experiments_tables as et
from aclvec.plans.catalog_parts import mod4
from aclvec.plans.catalog_policy import queries_n1
from aclvec.sources.tables import vectors


def rows(df):
    return sorted(tuple(tuple(x) if isinstance(x, list) else x for x in r) for r in df.collect())


def plain_lines(spark, sf_dir, d):
    """Words as rows, dense by a map of buckets, divided by the norm."""
    m = cs.text_vectors(spark, sf_dir, d).groupBy("doc_id", "line_no").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "weight"))).alias("m"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.element_at("m", i.cast("long")), F.lit(0.0)))
    norm = F.sqrt(F.aggregate("e", F.lit(0.0), lambda a, x: a + x * x))
    return m.select("doc_id", "line_no", dense.alias("e")).filter(norm > 0).select("doc_id", "line_no", F.transform("e", lambda x: (x / norm).cast("float")).alias("embedding"))


@pytest.mark.parametrize("size", [40, 1_000_000])
def test_lines_as_words_give_them(spark, tmp_path, monkeypatch, size):
    """Blank lines, letters of other alphabets, no text, words that cancel out, ids that come twice, texts in pieces."""
    texts = ["", None, "\n\n", "one two\n\nThree", "ÄbcéD Kİx Σas\n-7-", "ab\nbb aab", "a b", "\nlast", "word", "ends here\n", "x" * 300 + " y\nz"]
    given = [(i, x) for i, x in enumerate(texts)] + [(3, "four\nfive six\nseven\nEight nine"), (9, None), (3, "ten")]
    spark.createDataFrame(given, "doc_id long, text string").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    monkeypatch.setattr(cs, "TEXT_BYTES", size)
    found = rows(cs.line_vectors(spark, str(tmp_path), 64))
    assert found == rows(plain_lines(spark, str(tmp_path), 64))
    assert len(found) > 10


def test_lines_of_the_documents(spark, sf):
    assert rows(cs.line_vectors(spark, sf, 64)) == rows(plain_lines(spark, sf, 64))


@pytest.mark.parametrize("shift", [0.0, 3000.0])
def test_one_scan_places_in_several_partitionings(spark, sf, monkeypatch, shift):
    """Also where vectors lie so far from the origin that single precision does not tell them apart."""
    monkeypatch.setattr(sc, "CHUNK", 32)
    monkeypatch.setattr(sc, "PIECE", 8)
    monkeypatch.setattr(sc, "BLOCK", 8)
    monkeypatch.setattr(sc, "MARKED", 16)
    moved = lambda c: F.transform(c, lambda x: F.round(x * 8) / 8 + shift)
    v, q = (df.withColumn(c, moved(c).cast("array<float>")) for df, c in ((vectors(spark, sf), "embedding"), (queries_n1(spark, sf), "qvec")))
    p = g.natural_n1(spark, sf)
    truth = se.ground_truth(q, v, p).cache()
    assert rows(sc.ground_truth(q, v, p)) == rows(truth)
    several = [single_partition(p), role_homes(p, mod4(p)), role_partition(p)]
    placed = sc.true_places_in_each(q, v, p, several, truth).cache()
    for i, part in enumerate(several):
        found, plain = (df.select("ef", F.round("recall", 9)) for df in (sc.recalls(placed.filter(F.col("which") == i), [1, 5, 20]), se.recall_by_depth(q, v, p, part, truth, [1, 5, 20])))
        assert rows(found) == rows(plain)


def test_corpus_is_scanned_once_for_its_places(spark, sf, monkeypatch):
    """Every line meets a query once, however many partitionings hold it."""
    scans, places = [], sc._places
    monkeypatch.setattr(sc, "_places", lambda *a: scans.append(a) or places(*a))
    assert et.exp_text_corpus(spark, sf).count() == 18
    assert len(scans) == 1
