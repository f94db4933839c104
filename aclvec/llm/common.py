"""Reading, durable intermediate tables and text batches, shared by the operators of this package."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker handles at a time.
CHUNK_BYTES = 1 << 21


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark alone."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A new path in the folder that driver and executors share. Where none is set, a temporary one serves a local session; on a cluster it is an error."""
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="aclvec-shared-")
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def stored(df: DataFrame, compression: str = "snappy", group_bytes: int = 128 << 20) -> DataFrame:
    """`df` written once as Parquet in the shared folder and read back: cuts the lineage and survives lost executors.

    `group_bytes`: of a row group, which a writer holds in memory; less for wide rows.
    """
    path = shared_dir(df.sparkSession)
    df.write.option("parquet.block.size", group_bytes).parquet(path, compression=compression)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def narrow_batches(spark: SparkSession, rows: int = 1_000) -> None:
    """Fewer rows in an Arrow batch, for binary columns of several kilobytes: JVM and Python each hold a whole batch or two of every running task. Results do not depend on it."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(name)) > rows or int(spark.conf.get(name)) <= 0:
        spark.conf.set(name, rows)


def crc_mod(doc_id: Column | str, n: int) -> Column:
    """crc32 of the id's decimal text, modulo n: the fold of a document."""
    return F.crc32(F.col(doc_id).cast("string") if isinstance(doc_id, str) else doc_id.cast("string")) % n


def id_and_bytes(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, the whole text as UTF-8 bytes (null: empty) and the named further columns."""
    return docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"), *more)


def chunks(batch: pa.RecordBatch, column: str = "text", limit: int = CHUNK_BYTES) -> Iterator[tuple[slice, list[bytes]]]:
    """Runs of rows whose texts hold about `limit` bytes together; a longer text makes a run of its own."""
    texts = batch.column(batch.schema.get_field_index(column))
    begin = held = 0
    for i, n in enumerate(pc.binary_length(texts).to_pylist()):
        if i > begin and held + n > limit:
            yield slice(begin, i), texts.slice(begin, i - begin).to_pylist()
            begin, held = i, 0
        held += n
    if begin < len(texts):
        yield slice(begin, len(texts)), texts.slice(begin).to_pylist()


def per_text(frame: DataFrame, schema: str, make: Callable[[], Callable[[list[bytes]], dict[str, object]]]) -> DataFrame:
    """All columns of `frame` but its bytes column `text`, with the columns of `schema` that `make()` computes for each text.

    Columns of `frame` with such a name are replaced. `make` runs once a task and returns the function of a run of texts.
    """
    spark = frame.sparkSession
    added = spark.createDataFrame([], schema).schema
    frame = frame.drop(*added.names)
    out = type(frame.schema)([*(f for f in frame.schema if f.name != "text"), *added])
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(out)
    kept = [f.name for f in frame.schema if f.name != "text"]
    names = [f.name for f in added]

    def run(batches):
        work = make()
        for b in batches:
            for rows, texts in chunks(b):
                got = work(texts)
                part = b.slice(rows.start, rows.stop - rows.start)
                cols = [part.column(part.schema.get_field_index(k)) for k in kept]
                cols = [c if c.type == arrow.field(k).type else c.cast(arrow.field(k).type) for k, c in zip(kept, cols, strict=True)]
                cols += [pa.array(got[k], type=arrow.field(k).type) for k in names]
                yield pa.RecordBatch.from_arrays(cols, schema=arrow)

    return frame.mapInArrow(run, out)


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The texts in one array of bytes, each closed by a newline, and the offsets at which they begin (with the end)."""
    buf = np.frombuffer(b"\n".join(texts) + b"\n", dtype=np.uint8)
    sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts)) + 1
    return buf, np.concatenate(([0], np.cumsum(sizes)))


def sampled(rows: DataFrame, n_rows: int, bound: int, key: str = "doc_id", salt: int = 17) -> DataFrame:
    """About `bound` of the `n_rows` rows at most, chosen by a hash of `key`; all of them if they are fewer."""
    if n_rows <= bound:
        return rows
    return rows.filter(F.pmod(F.xxhash64(F.lit(salt), F.col(key)), F.lit(1 << 30)) < int(bound / n_rows * (1 << 30)))
