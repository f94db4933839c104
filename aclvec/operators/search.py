"""Secure top-k search: route, search each partition, filter, merge. Also the truth to compare with.

A query frame has query_id, user_id, k and qvec. Every result has passed the
permission test against the policy given, whatever the partitions hold.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from aclvec.functions.vector import METRICS
from aclvec.operators.partitioning import Partitioning
from aclvec.operators.policy import Policy, user_role_sets

#: Queries of one batch that are sent to every task.
MAX_BROADCAST_QUERIES = 20_000
#: Candidates that a scanning task holds before it hands them on; the merge does not depend on it.
MAX_HELD = 4_000_000


def small(queries: DataFrame) -> DataFrame:
    """A batch of queries, broadcast behind a check of its size; larger ones are left to a shuffle join."""
    return F.broadcast(queries) if queries.limit(MAX_BROADCAST_QUERIES + 1).count() <= MAX_BROADCAST_QUERIES else queries


def ranked(rows: DataFrame, limit, by: tuple[str, ...] = ("query_id",), dist: str = "dist") -> DataFrame:
    """The first `limit` rows of each group by distance, then id; planned with a group limit before the shuffle."""
    w = Window.partitionBy(*by).orderBy(F.round(dist, 6), "doc_id")
    return rows.withColumn("rank", F.row_number().over(w).cast("long")).filter(F.col("rank") <= limit)


def knn(queries: DataFrame, vectors: DataFrame, k: int, metric: str = "l2sq") -> DataFrame:
    """query_id, rank, doc_id, dist of the k nearest of all vectors. A batch of queries against all rows."""
    rows = vectors.select("doc_id", "embedding").join(small(queries.select("query_id", "qvec")))
    scored = rows.select("query_id", "doc_id", METRICS[metric]("embedding", "qvec").alias("dist"))
    return ranked(scored, k).select("query_id", "rank", "doc_id", F.round("dist", 6).alias("dist"))


def query_role_sets(queries: DataFrame, p: Policy) -> DataFrame:
    """user_id, rs of the users that ask, and of no others."""
    users = queries.select("user_id").distinct()
    return user_role_sets(p.but(ua=p.ua.join(users, "user_id", "left_semi"))).select("user_id", "rs")


def permitted_pairs(queries: DataFrame, p: Policy) -> DataFrame:
    """query_id, doc_id: what the users of the queries may see."""
    return queries.select("query_id", "user_id").join(p.ua, "user_id").join(p.pa, "role_id").select("query_id", "doc_id").distinct()


def ground_truth(queries: DataFrame, vectors: DataFrame, p: Policy, k: int | None = None, metric: str = "l2sq") -> DataFrame:
    """The k nearest permitted documents of each query; all of them if there are fewer. Filter first, then distances."""
    rows = permitted_pairs(queries, p).join(vectors.select("doc_id", "embedding"), "doc_id").join(small(queries.select("query_id", "k", "qvec")), "query_id")
    scored = rows.select("query_id", "k", "doc_id", METRICS[metric]("embedding", "qvec").alias("dist"))
    return ranked(scored, F.col("k") if k is None else k).select("query_id", "rank", "doc_id", F.round("dist", 6).alias("dist"))


prefilter = ground_truth


def routed_queries(queries: DataFrame, p: Policy, part: Partitioning) -> DataFrame:
    """query_id, rs, part, k, qvec: a row for each partition to search."""
    rs = queries.join(query_role_sets(queries, p), "user_id")
    return rs.join(part.route, "rs").select("query_id", "rs", "part", "k", "qvec")


def candidates(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, ef: int | None, metric: str = "l2sq") -> DataFrame:
    """query_id, rs, part, doc_id, dist: the ef nearest documents of each searched partition (all, if ef is None), by an exact scan."""
    copies = part.part_doc.join(vectors.select("doc_id", "embedding"), "doc_id")
    rows = copies.join(small(routed_queries(queries, p, part)), "part")
    scored = rows.select("query_id", "rs", "part", "doc_id", METRICS[metric]("embedding", "qvec").alias("dist"))
    return scored if ef is None else ranked(scored, ef, ("query_id", "part")).drop("rank")


def scan_candidates(copies: DataFrame, asked: DataFrame, ef: int | None) -> DataFrame:
    """The same as `candidates` for rows (part, doc_id, embedding) and routed queries, by matrix products in Arrow batches.

    The routed queries of a block go to every task; each task keeps the ef
    nearest of its rows, so vectors are never shuffled, only ef rows a task,
    query and partition. Beyond `MAX_BROADCAST_QUERIES` queries are asked block by block.
    """
    n_blocks = -(-asked.count() // MAX_BROADCAST_QUERIES)
    if n_blocks > 1:
        found, n_blocks = None, 2 * n_blocks  # room for uneven blocks
        for i in range(n_blocks):
            one = _scan(copies, asked.filter(F.pmod(F.xxhash64(F.lit(43), "query_id"), F.lit(n_blocks)) == i), ef)
            found = one if found is None else found.unionByName(one)
    else:
        found = _scan(copies, asked, ef)
    return found if ef is None else ranked(found, ef, ("query_id", "part")).drop("rank")


def _scan(copies: DataFrame, asked: DataFrame, ef: int | None) -> DataFrame:
    """The ef nearest rows that each task finds, for one block of queries; more where it holds `MAX_HELD` before its end."""
    by_part: dict[str, list] = {}
    for r in asked.select("query_id", "rs", "part", "qvec").collect():
        by_part.setdefault(r.part, []).append((r.query_id, r.rs, r.qvec))
    packed = {k: (np.array([x[0] for x in v]), [x[1] for x in v], np.array([x[2] for x in v], np.float64)) for k, v in by_part.items()}
    spark = copies.sparkSession
    sent, bound = spark.sparkContext.broadcast(packed), 0 if ef is None else MAX_HELD  # without a depth nothing is dropped, so nothing is held
    schema = pa.schema([("query_id", pa.int64()), ("rs", pa.string()), ("part", pa.string()), ("doc_id", pa.int64()), ("dist", pa.float64())])

    def nearest(ids: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The first ef by rounded distance, then id."""
        if ef is None:
            return ids, d
        d6 = np.round(d, 6)
        if ef < len(ids):
            near = np.flatnonzero(d6 <= np.partition(d6, ef - 1)[ef - 1])
            ids, d, d6 = ids[near], d[near], d6[near]
        order = np.lexsort((ids, d6))[:ef]
        return ids[order], d[order]

    def emit(held: dict):
        for k, found in held.items():
            ids, sets, _ = sent.value[k]
            for at in range(0, len(found), 256):
                some = [(i, *found[i]) for i in range(at, min(at + 256, len(found))) if found[i] is not None]
                n = np.array([len(x) for _, x, _ in some])
                if n.sum():
                    yield pa.RecordBatch.from_arrays([
                        pa.array(np.repeat([ids[i] for i, _, _ in some], n), pa.int64()), pa.array(np.repeat(np.array([sets[i] for i, _, _ in some], object), n), pa.string()), pa.array([k] * int(n.sum()), pa.string()),
                        pa.array(np.concatenate([x for _, x, _ in some]), pa.int64()), pa.array(np.concatenate([d for _, _, d in some]), pa.float64()),
                    ], schema=schema)

    def run(batches):
        held: dict[str, list] = {}  # by partition: the nearest of every query so far
        n_held = 0
        for b in batches:
            codes = b.column(0).dictionary_encode()
            part, names = codes.indices.to_numpy(), codes.dictionary.to_pylist()
            docs = b.column(1).to_numpy()
            flat = b.column(2).flatten().to_numpy(zero_copy_only=False)
            x = flat.reshape(len(docs), -1).astype(np.float64) if len(docs) else flat
            for c, k in enumerate(names):
                if k not in sent.value:
                    continue
                rows = np.flatnonzero(part == c)
                _, sets, q = sent.value[k]
                norms = (x[rows] ** 2).sum(axis=1)[None]
                found = held.setdefault(k, [None] * len(sets))
                for at in range(0, len(sets), 256):
                    some = q[at : at + 256]
                    d = np.maximum(norms - 2 * some @ x[rows].T + (some**2).sum(axis=1)[:, None], 0.0)
                    for i, one in enumerate(d, start=at):
                        old = found[i]
                        new = nearest(docs[rows], one) if old is None else nearest(np.concatenate((old[0], docs[rows])), np.concatenate((old[1], one)))
                        n_held += len(new[0]) - (0 if old is None else len(old[0]))
                        found[i] = new
            if n_held > bound:
                yield from emit(held)
                held, n_held = {}, 0
        yield from emit(held)

    wanted = copies.filter(F.col("part").isin(*packed)) if packed else copies.limit(0)
    return wanted.select("part", "doc_id", "embedding").mapInArrow(run, "query_id bigint, rs string, part string, doc_id bigint, dist double")


def search_stored(copies: DataFrame, queries: DataFrame, p: Policy, part: Partitioning, ef: int | None = None, k: int = 10) -> DataFrame:
    """Secure search over stored partitions (part, doc_id, embedding): only the directories of routed partitions are read."""
    return merge(permitted_only(scan_candidates(copies, routed_queries(queries, p, part), ef), p), k)


def permitted_only(found: DataFrame, p: Policy) -> DataFrame:
    """Rows whose document the role set may see now: a semi-join of the candidates with the permission edges, on every path."""
    roles = F.explode(F.transform(F.split("rs", ","), lambda r: r.cast("int")))
    asked = found.select("rs", "doc_id").distinct().select("rs", "doc_id", roles.alias("role_id"))
    allowed = asked.join(p.pa, ["role_id", "doc_id"], "left_semi").select("rs", "doc_id").distinct()
    return found.join(allowed, ["rs", "doc_id"], "left_semi")


def merge(found: DataFrame, k) -> DataFrame:
    """The global top-k of what the partitions returned; a document found in several counts once."""
    one = found.groupBy("query_id", "doc_id").agg(F.min("dist").alias("dist"))
    return ranked(one, k).select("query_id", "rank", "doc_id", F.round("dist", 6).alias("dist"))


def secure_search(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, ef: int | None = None, k: int = 10, metric: str = "l2sq") -> DataFrame:
    """Route, take ef candidates of each partition, filter, merge. With ef of None or a whole partition the result is the truth."""
    return merge(permitted_only(candidates(queries, vectors, p, part, ef, metric), p), k)


def search_stats(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, ef: int, k: int = 10) -> DataFrame:
    """query_id, visited partitions, evaluated distances, candidates and those dropped by the filter."""
    found = candidates(queries, vectors, p, part, ef)
    kept = permitted_only(found, p).groupBy("query_id").agg(F.count("*").alias("kept"))
    seen = routed_queries(queries, p, part).join(part.sizes(), "part").groupBy("query_id").agg(F.count("*").alias("visited"), F.sum("n_docs").alias("evaluated"))
    out = found.groupBy("query_id").agg(F.count("*").alias("candidates"))
    return seen.join(out, "query_id", "left").join(kept, "query_id", "left").select("query_id", "visited", "evaluated", F.coalesce("candidates", F.lit(0)).alias("candidates"), (F.coalesce("candidates", F.lit(0)) - F.coalesce("kept", F.lit(0))).alias("dropped"))


def recall_by_depth(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, truth: DataFrame, efs: list[int]) -> DataFrame:
    """ef, recall of exact scans filtered afterwards, at all depths from one pass: a true neighbour is found from its best place on."""
    placed = ranked(candidates(queries, vectors, p, part, None), max(efs), ("query_id", "part")).groupBy("query_id", "doc_id").agg(F.min("rank").alias("place"))
    found = truth.select("query_id", "doc_id").join(placed, ["query_id", "doc_id"], "left")
    return mean_recalls(found, efs)


def mean_recalls(placed: DataFrame, efs: list[int]) -> DataFrame:
    """ef, recall from query_id and place of true neighbours: whole numbers are summed, then queries with as many neighbours in order, so that the mean is the same to the bit in whatever order rows come."""
    one = placed.groupBy("query_id").agg(F.count("*").alias("n"), *(F.count(F.when(F.col("place") <= e, 1)).alias(f"h{e}") for e in efs))
    alike = one.groupBy("n").agg(F.count("*").alias("q"), *(F.sum(f"h{e}").alias(f"h{e}") for e in efs))  # k rows at most
    listed = alike.agg(F.array_sort(F.collect_list(F.struct("n", "q", *(f"h{e}" for e in efs)))).alias("a"))
    total = lambda start, f: F.aggregate("a", start, lambda x, one: x + f(one))
    n = total(F.lit(0).cast("long"), lambda one: one["q"])
    points = F.array(*(F.struct(F.lit(e).alias("ef"), F.try_divide(total(F.lit(0.0), lambda one, e=e: one[f"h{e}"] / one["n"]), n).alias("recall")) for e in efs))
    return listed.select(F.inline(points))


def top_documents(queries: DataFrame, vectors: DataFrame, p: Policy, k: int, metric: str = "l2sq") -> DataFrame:
    """Results by document where documents own several vectors: the best vector of each counts."""
    rows = permitted_pairs(queries, p).join(vectors.select("doc_id", "embedding"), "doc_id").join(small(queries.select("query_id", "qvec")), "query_id")
    best = rows.groupBy("query_id", "doc_id").agg(F.min(METRICS[metric]("embedding", "qvec")).alias("dist"))
    return ranked(best, k).select("query_id", "rank", "doc_id", F.round("dist", 6).alias("dist"))


def tune_depth(target: float, start: float, evaluate, sweep: float = 0.4, steps: int = 5, rounds: int = 2) -> tuple[int, float]:
    """The least depth found that reaches the target recall: a sweep around the model's estimate, then bisection. `evaluate(ef)` runs one job."""
    tried: dict[int, float] = {}

    def ask(ef: float) -> float:
        n = max(1, round(ef))
        if n not in tried:
            tried[n] = evaluate(n)
        return tried[n]

    for i in range(steps):
        ask(start * (1 - sweep + 2 * sweep * i / (steps - 1)))
    while max(tried.values()) < target and max(tried) < 1 << 20:
        ask(max(tried) * 2)
    for _ in range(rounds):
        good = min((e for e, r in tried.items() if r >= target), default=None)
        low = max((e for e, r in tried.items() if r < target and (good is None or e < good)), default=None)
        if good is None or low is None or good - low <= 1:
            break
        ask((good + low) / 2)
    good = min((e for e, r in tried.items() if r >= target), default=max(tried))
    return good, tried[good]
