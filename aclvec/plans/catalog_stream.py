"""Streaming queries; their batch meaning is the oracle."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from aclvec.operators import generators as g
from aclvec.operators import partitioning as pt
from aclvec.operators import scan as sc
from aclvec.plans.policies_sql import POLICIES, with_
from aclvec.plans.registry import big, query
from aclvec.sources.tables import read, scratch, vectors
from aclvec.streaming import changes as ch

CHANGES = """ch AS (SELECT event_id AS seq, ts, CASE event_type WHEN 'signup' THEN 'add_user' WHEN 'error' THEN 'drop_user' WHEN 'purchase' THEN 'grant' WHEN 'click' THEN 'revoke' ELSE 'query' END AS op, user_id, user_id % 25 AS role_id, event_id % 500 AS doc_id FROM events)"""


def _dir(spark, sf_dir: str) -> tuple[str, object]:
    """Path and schema of a stream source. A file source reads folders, so the table is named by a pattern."""
    return f"{sf_dir}/events.parque[t]", read(spark, sf_dir, "events").schema


def stream(spark, sf_dir):
    path, schema = _dir(spark, sf_dir)
    return ch.event_stream(spark, path, schema)


def _name(prefix: str) -> str:
    return f"{prefix}_{uuid.uuid4().hex[:8]}"


@query("stream_policy_final_state", with_(CHANGES) + "SELECT user_id, role_id::BIGINT AS role_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id, role_id ORDER BY ts DESC, op = 'drop_user' DESC, seq DESC) AS r FROM ch WHERE op IN ('add_user', 'drop_user')) WHERE r = 1 AND op = 'add_user'")
def stream_policy_final_state(spark, sf_dir):
    order = F.struct("ts", (F.col("op") == "drop_user").cast("int").alias("removal"), "seq")
    rows = ch.to_changes(stream(spark, sf_dir)).filter(F.col("op").isin("add_user", "drop_user"))
    state = ch.finished(rows.groupBy("user_id", "role_id").agg(F.max_by("op", order).alias("op")), _name("state"))
    return state.filter("op = 'add_user'").select("user_id", big("role_id").alias("role_id"))


@query("stream_state_vs_batch", "SELECT 'differences' AS check_name, 0::BIGINT AS violations")
def stream_state_vs_batch(spark, sf_dir):
    """State written by batches against the same changes applied at once."""
    base = scratch(spark)
    q = ch.apply_policy_stream(ch.to_changes(stream(spark, sf_dir)), f"{base}/state", f"{base}/cp")
    q.awaitTermination()
    last = q.lastProgress
    n = last["batchId"] if isinstance(last, dict) else last.batchId
    state = spark.read.parquet(f"{base}/state/b{n}")
    batch = ch.last_changes(ch.to_changes(read(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))))
    cols = ["user_id", "role_id", "doc_id", "op"]
    a, b = state.select(*cols), batch.select(*cols)
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.lit("differences").alias("check_name"), F.count("*").alias("violations"))


@query("stream_member_states", with_(CHANGES) + "SELECT user_id, role_id::BIGINT AS role_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id, role_id ORDER BY ts DESC, op = 'drop_user' DESC, seq DESC) AS r FROM ch WHERE op IN ('add_user', 'drop_user')) WHERE r = 1 AND op = 'add_user'")
def stream_member_states(spark, sf_dir):
    """Membership by state kept per user; the last row of a pair is its state."""
    rows = ch.finished(ch.member_states(ch.to_changes(stream(spark, sf_dir))), _name("members"), "append")
    last = rows.groupBy("user_id", "role_id").agg(F.max_by("member", F.struct("ts", "removal", "seq")).alias("member"))
    return last.filter("member").select("user_id", big("role_id").alias("role_id"))


@query("stream_secure_search", with_(POLICIES["n1"], """queries AS (SELECT event_id AS query_id, user_id, embedding AS qvec FROM events JOIN embeddings ON vec_id = event_id % (SELECT count(*) FROM embeddings) WHERE event_type = 'view'),
allowed AS (SELECT DISTINCT query_id, qvec, doc_id FROM queries JOIN ua USING (user_id) JOIN pa USING (role_id)),
dist AS (SELECT query_id, doc_id, list_sum(list_transform(range(1, len(qvec) + 1), lambda i: (embedding[i]::DOUBLE - qvec[i]::DOUBLE) * (embedding[i]::DOUBLE - qvec[i]::DOUBLE))) AS d FROM allowed JOIN embeddings ON vec_id = doc_id)""") + "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY round(d, 6), doc_id) AS rank, doc_id, round(d, 6) AS dist FROM dist QUALIFY rank <= 10")
def stream_secure_search(spark, sf_dir):
    """Every view event as a query for its user, answered through partitions by role as it comes."""
    p, v = g.natural_n1(spark, sf_dir), vectors(spark, sf_dir)
    part = pt.role_partition(p)
    n = v.count()
    asked = stream(spark, sf_dir).filter("event_type = 'view'").select(F.col("event_id").alias("query_id"), "user_id", (F.col("event_id") % n).alias("doc_id"))

    def search(batch):
        queries = batch.join(v.select("doc_id", F.col("embedding").alias("qvec")), "doc_id").select("query_id", "user_id", F.lit(10).alias("k"), "qvec")
        return sc.secure_search(queries, v, p, part)

    base = scratch(spark)
    ch.search_stream(asked, search, f"{base}/answers", f"{base}/cp").awaitTermination()
    return spark.read.parquet(f"{base}/answers").select("query_id", "rank", "doc_id", "dist")


SINCE = "strftime({}, '%Y-%m-%d %H:%M:%S')"
for _kind, _sql in (
    ("tumbling", f"SELECT {SINCE.format('d')} AS start, user_id, count(*) AS n FROM (SELECT date_trunc('day', ts) AS d, user_id FROM events WHERE event_type = 'view') GROUP BY d, user_id"),
    ("sliding", f"SELECT {SINCE.format('s')} AS start, user_id, count(*) AS n FROM (SELECT time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - to_hours(12 * i) AS s, user_id FROM events, range(2) t(i) WHERE event_type = 'view') GROUP BY s, user_id"),
    ("session", f"SELECT {SINCE.format('min(ts)')} AS start, user_id, count(*) AS n FROM (SELECT *, sum(gap) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS gap FROM events WHERE event_type = 'view')) GROUP BY user_id, s"),
):
    @query(f"stream_{_kind}", _sql)
    def _windowed(spark, sf_dir, kind=_kind):
        out = ch.finished(ch.windowed(stream(spark, sf_dir), kind), _name(kind))
        return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "user_id", "n")


@query("stream_late_counts")
def stream_late_counts(spark, sf_dir):
    """Rows of closed windows in append mode, where every tenth event comes two hours late."""
    late = stream(spark, sf_dir).withColumn("ts", F.when(F.col("event_id") % 10 == 0, F.col("ts") - F.expr("interval 2 hours")).otherwise(F.col("ts")))
    return ch.finished(ch.windowed(late), _name("late"), "append").agg(F.count("*").alias("closed"), F.sum("n").alias("counted"))


@query("stream_interval_join", with_(CHANGES) + "SELECT q.seq AS q_seq, g.seq AS g_seq FROM ch q JOIN ch g ON q.user_id = g.user_id AND g.ts <= q.ts AND g.ts >= q.ts - INTERVAL 1 HOUR WHERE q.op = 'query' AND g.op = 'grant'")
def stream_interval_join(spark, sf_dir):
    rows = ch.to_changes(stream(spark, sf_dir))
    again = ch.to_changes(stream(spark, sf_dir))
    return ch.finished(ch.interval_join(rows.filter("op = 'query'"), again.filter("op = 'grant'")), _name("joined"), "append")


@query("stream_dedup", "SELECT count(DISTINCT user_id) AS users FROM events")
def stream_dedup(spark, sf_dir):
    rows = stream(spark, sf_dir).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["user_id"])
    return ch.finished(rows.select("user_id"), _name("dedup"), "append").agg(F.count("*").alias("users"))


@query("stream_late_repair", f"""WITH {CHANGES}, tops AS (SELECT seq % 4 AS part, max(ts) AS top FROM ch GROUP BY 1),
marks AS (SELECT a.part, max(b.top) AS mark FROM tops a JOIN tops b ON b.part < a.part GROUP BY a.part)
SELECT seq, op, coalesce(ts < mark - INTERVAL 1 HOUR, false) AS late FROM ch LEFT JOIN marks ON part = seq % 4""")
def stream_late_repair(spark, sf_dir):
    """The events as four files, one a batch: which changes come too late and go to the repair table."""
    base = scratch(spark)
    events = read(spark, sf_dir, "events")
    for i in range(4):
        events.filter(F.col("event_id") % 4 == i).coalesce(1).write.parquet(f"{base}/in/f{i}")
    rows = ch.to_changes(ch.event_stream(spark, f"{base}/in/*", events.schema))
    ch.repair_stream(rows, f"{base}/out", f"{base}/cp").awaitTermination()
    parts = [spark.read.parquet(f"{base}/out/{kind}").select("seq", "op", F.lit(kind == "repair").alias("late")) for kind in ("applied", "repair")]
    return parts[0].unionByName(parts[1])
