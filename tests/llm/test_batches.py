from aclvec.llm import media
from aclvec.llm.common import narrow_batches

NAME = "spark.sql.execution.arrow.maxRecordsPerBatch"


def test_media_goes_in_narrow_batches_with_the_same_results(spark, sf, monkeypatch):
    def rows():
        return sorted(tuple(r) for r in media.op2_media(spark, sf).collect())

    plain = spark.conf.get(NAME)
    try:
        narrow = rows()
        assert int(spark.conf.get(NAME)) == 1_000
        narrow_batches(spark, 7)
        assert int(spark.conf.get(NAME)) == 7
        narrow_batches(spark)  # never widened
        assert int(spark.conf.get(NAME)) == 7 and rows() == narrow
        spark.conf.set(NAME, 10_000)
        monkeypatch.setattr(media, "narrow_batches", lambda spark: None)
        assert rows() == narrow
    finally:
        spark.conf.set(NAME, plain)
