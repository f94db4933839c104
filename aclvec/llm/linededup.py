"""Line dedup through a sharded minimal perfect hash.

Each distinct line key has a 128-bit hash. One aggregation finds how many
documents hold a key and the smallest of them. Shards of these keys get a
minimal perfect hash: levels of bit arrays in which a key's bit stands alone,
its rank being its place in arrays of fingerprints, counts and owners.
Documents' keys are packed by shard and probe the arrays, many at a time; lines
are never joined with lines. A shard with many probes is copied to several
tasks, so that a line found in very many documents burdens none.

Defined results: a null or empty text is one empty line; rows that share an id
are one document (none of them loses a line to another); a null id counts as
the largest id. Extra columns stay.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.llm.common import chunks, id_and_bytes, stored, table

LEAST_CHARS = 10
#: Bounds of a shard's keys, shards wanted, and probes that a task takes.
SHARD_LEAST, SHARD_MOST, SHARDS, PROBES = 2_000, 500_000, 256, 100_000
GAMMA = 2.0
LAST_ID = (1 << 63) - 1


def line_key(line: bytes) -> bytes:
    """Stripped of ASCII white space, A-Z in lower case."""
    return line.strip().lower()


def long_enough(key: bytes) -> bool:
    if len(key) < LEAST_CHARS:
        return False
    return len(key) >= 4 * LEAST_CHARS or len(key.decode("utf-8", "replace")) >= LEAST_CHARS


def key_hash(key: bytes) -> bytes:
    return hashlib.blake2b(key, digest_size=16).digest()


def mixed(h: np.ndarray, level: int) -> np.ndarray:
    """Another hash of the same keys for each level."""
    x = h ^ np.uint64((0x9E3779B97F4A7C15 * (level + 1)) & 0xFFFFFFFFFFFFFFFF)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


class PerfectHash:
    """Places 0 .. n-1 for n distinct keys of two 64-bit halves; other keys get any place or -1."""

    def __init__(self, sizes: list[int], bits: np.ndarray):
        self.sizes, self.bits = sizes, bits
        ones = np.unpackbits(bits, bitorder="little")
        self.flags = ones.astype(bool)
        self.rank = np.concatenate(([0], np.cumsum(ones, dtype=np.int64)))

    @classmethod
    def build(cls, a: np.ndarray, b: np.ndarray) -> PerfectHash:
        left, sizes, parts = a ^ mixed(b, 99), [], []
        while len(left):
            size = max(8, int(GAMMA * len(left)) // 8 * 8)
            at = (mixed(left, len(sizes)) % np.uint64(size)).astype(np.int64)
            alone = np.bincount(at, minlength=size) == 1
            sizes.append(size)
            parts.append(alone)
            left = left[~alone[at]]
            if len(sizes) > 200:
                raise ValueError("repeated keys")
        return cls(sizes, np.packbits(np.concatenate(parts) if parts else np.zeros(8, bool), bitorder="little"))

    def place(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = a ^ mixed(b, 99)
        out, open_, base = np.full(len(key), -1, np.int64), np.arange(len(key)), 0
        for level, size in enumerate(self.sizes):
            at = base + (mixed(key[open_], level) % np.uint64(size)).astype(np.int64)
            hit = self.flags[at]
            out[open_[hit]] = self.rank[at[hit]]
            open_, base = open_[~hit], base + size
            if not len(open_):
                break
        return out


def line_rows(docs: DataFrame) -> DataFrame:
    """id, h1, h2: each document's distinct keys of enough code points."""

    def run(batches):
        schema = pa.schema([("id", pa.int64()), ("h1", pa.int64()), ("h2", pa.int64())])
        for b in batches:
            ids = b.column(b.schema.get_field_index("id"))
            for rows, texts in chunks(b):
                out_ids: list[int] = []
                found: list[bytes] = []
                for i, t in zip(ids[rows].to_pylist(), texts, strict=True):
                    keys = {k for x in t.split(b"\n") if long_enough(k := line_key(x))}
                    out_ids += [i] * len(keys)
                    found += map(key_hash, keys)
                h = np.frombuffer(b"".join(found), np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(out_ids, pa.int64()), pa.array(h[:, 0]), pa.array(h[:, 1])], schema=schema)

    return id_and_bytes(docs).select(F.coalesce("doc_id", F.lit(LAST_ID)).alias("id"), "text").mapInArrow(run, "id long, h1 long, h2 long")


def build_index(lines: DataFrame) -> tuple[DataFrame, int]:
    """A row for each shard: its perfect hash and arrays of fingerprints, counts and owners; and the number of shards."""
    keys = stored(lines.groupBy("h1", "h2").agg(F.count("*").alias("n"), F.min("id").alias("owner"), F.max("id").alias("last")))
    n_keys = keys.count()
    n_shards = max(1, -(-n_keys // min(SHARD_MOST, max(SHARD_LEAST, n_keys // SHARDS))))

    def build(key, rows):
        col = lambda c: rows[c].to_numpy()
        a, b = col("h1").view(np.uint64), col("h2").view(np.uint64)
        ph = PerfectHash.build(a, b)
        at = ph.place(a, b)
        fp, n, owner = np.empty(len(a), np.uint64), np.empty(len(a), np.uint32), np.empty(len(a), np.int64)
        fp[at], n[at] = b, np.minimum(col("n"), 0xFFFFFFFF)
        # A key of one document alone, however often, owns itself: count 1.
        n[at[col("owner") == col("last")]] = 1
        owner[at] = col("owner")
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int64()), "sizes": pa.array([ph.sizes], pa.list_(pa.int32())), "bits": [ph.bits.tobytes()], "fp": [fp.tobytes()], "n": [n.tobytes()], "owner": [owner.tobytes()]})

    index = keys.withColumn("shard", F.pmod("h1", F.lit(n_shards))).groupBy("shard").applyInArrow(build, "shard long, sizes array<int>, bits binary, fp binary, n binary, owner binary")
    return stored(index), n_shards


def probes(lines: DataFrame, n_shards: int) -> DataFrame:
    """Packed keys: shard, seq, n_probes, ids, h1 and h2 as arrays of 64-bit numbers in bytes."""

    def run(batches):
        schema = pa.schema([("shard", pa.int64()), ("seq", pa.int64()), ("n_probes", pa.int64()), *((k, pa.binary()) for k in ("ids", "h1", "h2"))])
        for b in batches:
            cols = [b.column(b.schema.get_field_index(k)).to_numpy() for k in ("id", "h1", "h2")]
            shard = cols[1] % n_shards
            order = np.argsort(shard, kind="stable")
            shard, cols = shard[order], [c[order] for c in cols]
            starts = np.flatnonzero(np.concatenate(([True], shard[1:] != shard[:-1]))) if len(shard) else np.zeros(0, np.int64)
            ends = np.concatenate((starts[1:], [len(shard)])) if len(shard) else starts
            seq = int(cols[0].sum() + cols[2].sum()) & 0x7FFFFFFF if len(shard) else 0
            spans = list(zip(starts.tolist(), ends.tolist(), strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(shard[starts], pa.int64()), pa.array([seq] * len(spans), pa.int64()), pa.array([e - s for s, e in spans], pa.int64()), *(pa.array([c[s:e].tobytes() for s, e in spans], pa.binary()) for c in cols)], schema=schema)

    return lines.mapInArrow(run, "shard long, seq long, n_probes long, ids binary, h1 binary, h2 binary")


def to_drop(lines: DataFrame) -> DataFrame:
    """id and key (its 16 bytes) of the keys that a document loses: found in another document with a smaller id."""
    lines = stored(lines)
    index, n_shards = build_index(lines)
    packed = probes(lines, n_shards)
    loads = packed.groupBy("shard").agg(F.sum("n_probes").alias("load")).select("shard", F.ceil(F.col("load") / PROBES).cast("int").alias("copies"))
    loads = stored(loads)
    asked = packed.join(loads, "shard").withColumn("copy", F.pmod(F.xxhash64("seq"), "copies").cast("int")).drop("copies", "seq", "n_probes")
    held = index.join(loads, "shard").withColumn("copy", F.explode(F.sequence(F.lit(0), F.col("copies") - 1))).drop("copies")

    def probe(key, asked, held):
        lost_ids, lost_keys = [np.zeros(0, np.int64)], [np.zeros((0, 2), np.int64)]
        if held.num_rows:
            row = held.slice(0, 1).to_pylist()[0]
            ph = PerfectHash(row["sizes"], np.frombuffer(row["bits"], np.uint8))
            fp, n, owner = np.frombuffer(row["fp"], np.uint64), np.frombuffer(row["n"], np.uint32), np.frombuffer(row["owner"], np.int64)
            for ids, h1, h2 in zip(*(asked[k].to_pylist() for k in ("ids", "h1", "h2")), strict=True):
                ids, a, b = np.frombuffer(ids, np.int64), np.frombuffer(h1, np.uint64), np.frombuffer(h2, np.uint64)
                at = ph.place(a, b)
                known = at >= 0
                known &= fp[np.maximum(at, 0)] == b
                lost = known & (n[np.maximum(at, 0)] > 1) & (owner[np.maximum(at, 0)] != ids)
                lost_ids.append(ids[lost])
                lost_keys.append(np.stack((a[lost], b[lost]), axis=1).view(np.int64))
        keys = pa.FixedSizeBinaryArray.from_buffers(pa.binary(16), sum(map(len, lost_ids)), [None, pa.py_buffer(np.concatenate(lost_keys).tobytes())])
        return pa.table({"id": np.concatenate(lost_ids), "key": keys.cast(pa.binary())})

    return asked.groupBy("shard", "copy").cogroup(held.groupBy("shard", "copy")).applyInArrow(probe, "id long, key binary")


def dedup_lines(docs: DataFrame, digests: bool = False) -> DataFrame:
    """`docs` with n_lines and n_dropped, and its `text` without the dropped lines; with `digests`, doc_id and the text's hash only."""
    lost = to_drop(line_rows(docs)).groupBy("id").agg(F.collect_list("key").alias("lost_keys"))
    more = [] if digests else [c for c in docs.columns if c not in ("doc_id", "text")]
    names = {c: f"own_{i}" for i, c in enumerate(more)}
    kept = id_and_bytes(docs, *(F.col(f"`{c}`").alias(n) for c, n in names.items())).withColumn("lost_id", F.coalesce("doc_id", F.lit(LAST_ID)))
    both = kept.join(lost.withColumnRenamed("id", "lost_id"), "lost_id", "left").drop("lost_id")

    def rest(t: bytes, lost) -> tuple[int, int, bytes]:
        lines = t.split(b"\n")
        if not lost:
            return len(lines), 0, t
        gone = set(lost)
        left = [x for x in lines if not (long_enough(k := line_key(x)) and key_hash(k) in gone)]
        return len(lines), len(lines) - len(left), b"\n".join(left)

    result = "kept_sha256 string" if digests else "text_out string"
    names_out = [c for c in both.columns if c not in ("text", "lost_keys")]
    types = {f.name: f for f in both.schema}
    out_schema = type(both.schema)([*(types[c] for c in names_out), *both.sparkSession.createDataFrame([], f"n_lines long, n_dropped long, {result}").schema])
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(out_schema)

    def run(batches):
        for b in batches:
            lost_keys = b.column(b.schema.get_field_index("lost_keys"))
            for rows, texts in chunks(b):
                got = [rest(t, lost) for t, lost in zip(texts, lost_keys[rows].to_pylist(), strict=True)]
                last = [hashlib.sha256(x[2]).hexdigest() for x in got] if digests else [x[2].decode("utf-8", "replace") for x in got]
                cols = [b.column(b.schema.get_field_index(c))[rows].cast(arrow.field(c).type) for c in names_out]
                yield pa.RecordBatch.from_arrays([*cols, pa.array([x[0] for x in got], pa.int64()), pa.array([x[1] for x in got], pa.int64()), pa.array(last, pa.string())], schema=arrow)

    out = both.mapInArrow(run, out_schema)
    if digests:
        return out
    back = {n: c for c, n in names.items()}
    cols = [F.col("text_out").alias("text") if c == "text" else F.col("doc_id") if c == "doc_id" else F.col(names[c]).alias(c) for c in docs.columns]
    return out.select(*cols, *(F.col(c) for c in ("n_lines", "n_dropped") if c not in back.values()))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is left of every whole text once lines of other documents are dropped."""
    return dedup_lines(table(spark, sf_dir, "documents"), digests=True)


ORACLE = r"""
WITH lines AS (
    SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
           generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS nr
    FROM documents
), keyed AS (
    SELECT doc_id, nr, line,
           translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
    FROM lines
), owners AS (
    SELECT k, min(doc_id) AS owner FROM keyed WHERE length(k) >= 10 GROUP BY k HAVING count(DISTINCT doc_id) >= 2
), marked AS (
    SELECT keyed.*, coalesce(owner <> doc_id, false) AS dropped FROM keyed LEFT JOIN owners USING (k)
)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (dropped) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY nr) FILTER (NOT dropped), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
