"""Counts by role sets and access classes against counts of pairs of users and documents."""

import pytest
from pyspark.sql import functions as F

from aclvec.operators import generators as g
from aclvec.operators import partitioning as pt
from aclvec.operators import policy as pol


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(params=["h1", "n1"])
def p(request, spark, sf):
    """With a user's edge twice, a role that opens nothing and a document that only it could open."""
    made = g.hand_h1(spark) if request.param == "h1" else g.natural_n1(spark, sf)
    more = spark.createDataFrame([(1, 1), (1, 1), (77, 999)], "user_id long, role_id int")
    return made.but(ua=made.ua.union(more), pa=made.pa.union(spark.createDataFrame([(998, 3)], "role_id int, doc_id long")))


def test_counts_equal_counts_of_pairs(p):
    pairs = pol.auth(p).cache()
    assert rows(pol.auth_counts(p)) == rows(pairs.groupBy("user_id").agg(F.count("*")))
    assert rows(pol.reader_counts(p)) == rows(pairs.groupBy("doc_id").agg(F.count("*")))
    assert rows(pt.per_user_sizes(p)) == rows(pt.per_user_partition(p).groupBy("part").agg(F.count("*")))
    assert pol.class_readers(p).agg(F.sum(F.col("n_docs") * F.col("n_users"))).first()[0] == pairs.count()


@pytest.mark.parametrize("key", ["auth_user_docs", "acl_expand", "acl_vs_role_edges", "part_per_user_overhead", "join_broadcast", "join_sortmerge"])
def test_equals_sql(same, key):
    same(key)
