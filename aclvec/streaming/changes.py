"""Policy changes and query logs as streams over the event files.

Changes are applied in the order of (ts, seq), and a revocation wins over a grant
of the same instant. State is written by batch; a batch that comes again changes
nothing.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Event types as changes.
OPS = {"signup": "add_user", "error": "drop_user", "purchase": "grant", "click": "revoke", "view": "query"}


def event_stream(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    """The events under `path` as a stream of files; ts as an instant in UTC."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def to_changes(events: DataFrame, n_roles: int = 25, n_docs: int = 500) -> DataFrame:
    """seq, ts, op, user_id, role_id, doc_id."""
    op = F.coalesce(*(F.when(F.col("event_type") == k, F.lit(v)) for k, v in OPS.items()))
    return events.select(F.col("event_id").alias("seq"), "ts", op.alias("op"), "user_id", (F.col("user_id") % n_roles).cast("int").alias("role_id"), (F.col("event_id") % n_docs).alias("doc_id"))


def membership(changes: DataFrame) -> DataFrame:
    """user_id, role_id of pairs whose last change is an addition."""
    own = changes.filter(F.col("op").isin("add_user", "drop_user"))
    w = Window.partitionBy("user_id", "role_id").orderBy(F.desc("ts"), (F.col("op") == "drop_user").desc(), F.desc("seq"))
    return own.withColumn("r", F.row_number().over(w)).filter("r = 1 and op = 'add_user'").select("user_id", "role_id")


def grants(changes: DataFrame) -> DataFrame:
    """role_id, doc_id of pairs whose last change is a grant."""
    own = changes.filter(F.col("op").isin("grant", "revoke"))
    w = Window.partitionBy("role_id", "doc_id").orderBy(F.desc("ts"), (F.col("op") == "revoke").desc(), F.desc("seq"))
    return own.withColumn("r", F.row_number().over(w)).filter("r = 1 and op = 'grant'").select("role_id", "doc_id")


def last_changes(changes: DataFrame) -> DataFrame:
    """The last change of each pair: what state needs to keep of a batch, by aggregation."""
    order = F.struct("ts", F.col("op").isin("drop_user", "revoke").cast("int").alias("removal"), "seq")
    users = changes.filter(F.col("op").isin("add_user", "drop_user")).groupBy("user_id", "role_id").agg(F.max_by("op", order).alias("op"), F.max(order).alias("o"))
    docs = changes.filter(F.col("op").isin("grant", "revoke")).groupBy("role_id", "doc_id").agg(F.max_by("op", order).alias("op"), F.max(order).alias("o"))
    cols = lambda df, u, d: df.select(u.alias("user_id"), "role_id", d.alias("doc_id"), "op", F.col("o.ts").alias("ts"), F.col("o.seq").alias("seq"))
    none = F.lit(None).cast("long")
    return cols(users, F.col("user_id"), none).union(cols(docs, none, F.col("doc_id")))


def apply_policy_stream(changes: DataFrame, path: str, checkpoint: str):
    """Keeps the last change of every pair under `path`, one directory a batch; a batch that is run again overwrites its own directory."""

    def put(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        new = last_changes(batch)
        if batch_id:  # every batch writes its directory, so one that is missing is an error and not an empty state
            new = new.unionByName(spark.read.parquet(f"{path}/b{batch_id - 1}"))
        last_changes(new).write.mode("overwrite").parquet(f"{path}/b{batch_id}")

    return changes.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


MEMBERS = "user_id bigint, role_id int, member boolean, ts bigint, removal int, seq bigint"


def member_states(changes: DataFrame) -> DataFrame:
    """MEMBERS rows whenever a user's membership of a role changes, from state kept per user: the last change of each of the user's roles."""
    own = changes.filter(F.col("op").isin("add_user", "drop_user"))
    rows = own.select("user_id", "role_id", F.unix_micros("ts").alias("ts"), (F.col("op") == "drop_user").cast("int").alias("removal"), "seq")

    def run(key, frames, state):
        held = {r: (t, d, s) for r, t, d, s in zip(*state.get, strict=True)} if state.exists else {}
        changed = set()
        for f in frames:
            for r, *at in f[["role_id", "ts", "removal", "seq"]].itertuples(index=False, name=None):
                if r not in held or tuple(at) > held[r]:
                    held[r] = tuple(at)
                    changed.add(r)
        state.update(tuple(list(c) for c in zip(*((r, *at) for r, at in sorted(held.items())), strict=True)))
        out = [(key[0], r, not held[r][1], *held[r]) for r in sorted(changed)]
        yield pd.DataFrame(out, columns=["user_id", "role_id", "member", "ts", "removal", "seq"])

    state = "role_id array<int>, ts array<bigint>, removal array<int>, seq array<bigint>"
    return rows.groupBy("user_id").applyInPandasWithState(run, MEMBERS, state, "append", "NoTimeout")


def repair_stream(changes: DataFrame, path: str, checkpoint: str, lateness: str = "1 hour"):
    """Deals changes to `path`/applied and `path`/repair: a change goes to repair if earlier batches hold one that is later by more than `lateness`.

    `path`/marks keeps each batch's latest instant. A batch that is run again overwrites its own directories.
    """

    def put(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        mark = None
        if batch_id:
            mark = spark.read.parquet(f"{path}/marks/batch={batch_id - 1}").first()[0]
        late = F.lit(False) if mark is None else F.coalesce(F.col("ts") < F.lit(mark) - F.expr(f"interval {lateness}"), F.lit(False))
        batch.filter(~late).write.mode("overwrite").parquet(f"{path}/applied/batch={batch_id}")
        batch.filter(late).write.mode("overwrite").parquet(f"{path}/repair/batch={batch_id}")
        top = batch.agg(F.max("ts").alias("ts")).select(F.greatest("ts", F.lit(mark).cast("timestamp")).alias("ts"))
        top.write.mode("overwrite").parquet(f"{path}/marks/batch={batch_id}")

    return changes.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def search_stream(queries: DataFrame, search, path: str, checkpoint: str):
    """Answers a stream of queries batch by batch with `search(batch)`, under `path`; a batch that is run again overwrites its own directory."""

    def put(batch: DataFrame, batch_id: int) -> None:
        search(batch).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return queries.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed(events: DataFrame, kind: str = "tumbling", lateness: str = "1 hour") -> DataFrame:
    """start, user_id, n of queries per user: tumbling days, sliding half days or sessions."""
    w = {"tumbling": lambda: F.window("ts", "1 day"), "sliding": lambda: F.window("ts", "1 day", "12 hours"), "session": lambda: F.session_window("ts", "6 hours")}[kind]()
    out = events.filter("event_type = 'view'").withWatermark("ts", lateness).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n"))
    return out.select(F.col("w.start").alias("start"), "user_id", "n")


def interval_join(queries: DataFrame, granted: DataFrame, hours: int = 1) -> DataFrame:
    """Queries with a grant to the same user within the hours before: a join of two streams within watermarks."""
    q = queries.select(F.col("seq").alias("q_seq"), F.col("ts").alias("q_ts"), F.col("user_id").alias("q_user")).withWatermark("q_ts", "1 hour")
    g = granted.select(F.col("seq").alias("g_seq"), F.col("ts").alias("g_ts"), F.col("user_id").alias("g_user")).withWatermark("g_ts", "1 hour")
    return q.join(g, (F.col("q_user") == F.col("g_user")) & (F.col("g_ts") <= F.col("q_ts")) & (F.col("g_ts") >= F.col("q_ts") - F.expr(f"interval {hours} hours"))).select("q_seq", "g_seq")


def finished(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Runs a stream over all that is there and returns its memory table: for bounded results such as counts by window."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
