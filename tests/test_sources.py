import pytest
from pyspark.sql import functions as F

from aclvec.functions.register import register
from aclvec.operators import generators as g
from aclvec.schemas import checked
from aclvec.sources import snapshots
from aclvec.sources.policy_source import PolicySource


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_round_trip(spark, tmp_path, kind):
    pa = g.hand_h1(spark).pa
    snapshots.write_rows(pa, str(tmp_path / kind), kind)
    assert rows(snapshots.read_rows(spark, str(tmp_path / kind), kind, "role_id int, doc_id bigint").select("role_id", "doc_id")) == rows(pa)


def test_versions(spark, tmp_path):
    p = g.hand_h1(spark)
    snapshots.commit(p, str(tmp_path), 1)
    snapshots.commit(p.but(pa=p.pa.filter("role_id > 1")), str(tmp_path), 2)
    assert snapshots.latest(spark, str(tmp_path)) == 2
    assert snapshots.load(spark, str(tmp_path)).pa.count() == 10
    assert snapshots.load(spark, str(tmp_path), 1).pa.count() == 16


def test_data_source_and_table_function_agree(spark):
    spark.dataSource.register(PolicySource)
    register(spark)
    a = spark.read.format("aclvec-policy").option("roles", 6).option("docs", 300).option("max_docs", 40).load()
    assert rows(a) == rows(spark.sql("SELECT * FROM policy_generate(6, 300, 40)"))


def test_schemas_are_checked(spark):
    with pytest.raises(TypeError):
        checked(spark.range(3).select(F.col("id").alias("role_id"), F.col("id").alias("doc_id")), "pa")
