"""Plan shapes: semi-joins for permissions, limits before shuffles, filters in scans, no Python on the exact path."""

from pyspark.sql import functions as F

from aclvec.operators import generators as g
from aclvec.operators import policy as pol
from aclvec.operators import search as se
from aclvec.operators.partitioning import role_partition
from aclvec.plans.catalog_policy import queries_n1
from aclvec.sources.tables import read, vectors


def text(df) -> str:
    return df._jdf.queryExecution().toString()


def test_existence_becomes_a_semi_join(spark, sf):
    rows = read(spark, sf, "embeddings").select(F.col("vec_id").alias("doc_id"), "label")
    pol.rls_view(spark, g.natural_n1(spark, sf), rows, "plan_view", "7")
    assert "LeftSemi" in text(spark.sql("SELECT * FROM plan_view"))


def test_top_k_is_limited_before_the_shuffle_and_stays_in_the_jvm(spark, sf):
    plan = text(se.secure_search(queries_n1(spark, sf), vectors(spark, sf), g.natural_n1(spark, sf), role_partition(g.natural_n1(spark, sf)), 50))
    assert "WindowGroupLimit" in plan
    assert "Python" not in plan and "Arrow" not in plan


def test_filters_and_columns_reach_the_scan(spark, sf):
    plan = text(read(spark, sf, "documents").filter("n_chars > 2000 and lang = 'en'").select("doc_id"))
    assert "PushedFilters: [IsNotNull(n_chars), IsNotNull(lang), GreaterThan(n_chars,2000), EqualTo(lang,en)]" in plan
    assert "text" not in plan.split("ReadSchema")[-1]


def test_partition_directories_are_pruned(spark, sf, tmp_path):
    from aclvec.operators.partitioning import materialise

    p = g.natural_n1(spark, sf)
    materialise(role_partition(p), vectors(spark, sf).select("doc_id", "embedding"), str(tmp_path / "parts"))
    rows = spark.read.parquet(str(tmp_path / "parts"))
    asked = spark.createDataFrame([(3,)], "part int").filter("part < 10")
    assert "dynamicpruning" in text(rows.join(F.broadcast(asked), "part"))


def test_bucketed_tables_join_without_a_shuffle(spark, sf):
    from aclvec.plans.catalog_relational import join_bucketed

    join_bucketed(spark, sf)  # writes the tables
    edges, nodes = spark.table("aclvec_edges"), spark.table("aclvec_nodes")
    plan = edges.hint("merge").join(nodes, "doc_id")._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan
