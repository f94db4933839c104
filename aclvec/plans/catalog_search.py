"""Queries over vectors, indexes, secure search and updates."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F

from aclvec.functions import vector as vec
from aclvec.functions.models import RecallModel
from aclvec.operators import generators as g
from aclvec.operators import indexes as ix
from aclvec.operators import measures as me
from aclvec.operators import partitioning as pt
from aclvec.operators import planner as pl
from aclvec.operators import policy as pol
from aclvec.operators import routing as ro
from aclvec.operators import scan as sc
from aclvec.operators import search as se
from aclvec.operators import updates as up
from aclvec.plans.catalog_parts import mod4, n1, parts, sql
from aclvec.plans.catalog_policy import queries_n1
from aclvec.plans.policies_sql import MEASURED, PARTS, POLICIES, SETS, TRUTH, distances, with_
from aclvec.plans.registry import big, query, r6, violations, zeros
from aclvec.sources.tables import read, scratch, vectors

#: Bytes of text that are made vectors at once.
TEXT_BYTES = 1_000_000

DIST = with_(POLICIES["n1"], distances())


@query("knn_exact", DIST + "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY round(d, 6), doc_id) AS rank, doc_id, round(d, 6) AS dist FROM dist QUALIFY rank <= 10")
def knn_exact(spark, sf_dir):
    return sc.knn(queries_n1(spark, sf_dir), vectors(spark, sf_dir), 10)


_PAIR = "list_sum(list_transform(range(1, 65), lambda i: {}))"
_DISTS = {"l2": "sqrt(" + _PAIR.format("(a.embedding[i]::DOUBLE - b.embedding[i]) * (a.embedding[i]::DOUBLE - b.embedding[i])") + ")", "dot": _PAIR.format("a.embedding[i]::DOUBLE * b.embedding[i]::DOUBLE"), "cosine": _PAIR.format("a.embedding[i]::DOUBLE * b.embedding[i]::DOUBLE") + " / (sqrt(" + _PAIR.format("a.embedding[i]::DOUBLE * a.embedding[i]::DOUBLE") + ") * sqrt(" + _PAIR.format("b.embedding[i]::DOUBLE * b.embedding[i]::DOUBLE") + "))"}
for _name, _f in (("l2", vec.l2), ("dot", vec.dot), ("cosine", vec.cosine)):
    @query(f"dist_{_name}", f"SELECT a.vec_id, round({_DISTS[_name]}, 6) AS d FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
    def _dist(spark, sf_dir, f=_f):
        e = read(spark, sf_dir, "embeddings").select("vec_id", "embedding")
        nxt = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
        return e.join(nxt, "vec_id").select("vec_id", r6(f("embedding", "other")).alias("d"))


@query("vec_norms", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm FROM embeddings")
def vec_norms(spark, sf_dir):
    return read(spark, sf_dir, "embeddings").select("vec_id", r6(vec.norm("embedding")).alias("norm"))


@query("vec_label_mean", "SELECT label, i::BIGINT AS dim, round(avg(embedding[i]::DOUBLE), 6) AS mean FROM embeddings, range(1, 65) t(i) GROUP BY label, i")
def vec_label_mean(spark, sf_dir):
    rows = read(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("dim", "x"))
    return rows.groupBy("label", (F.col("dim") + 1).cast("long").alias("dim")).agg(r6(F.avg(F.col("x").cast("double"))).alias("mean"))


@query("range_search_radius", DIST + "SELECT query_id, doc_id, round(d, 6) AS dist FROM dist WHERE round(d, 6) <= 1.2")
def range_search_radius(spark, sf_dir):
    rows = vectors(spark, sf_dir).select("doc_id", "embedding").join(se.small(queries_n1(spark, sf_dir).select("query_id", "qvec")))
    return rows.select("query_id", "doc_id", r6(vec.l2sq("embedding", "qvec")).alias("dist")).filter("dist <= 1.2")


ANSWER = with_(POLICIES["n1"], distances(), TRUTH) + "SELECT query_id, rank, doc_id, dist FROM truth"


def truth_n1(spark, sf_dir, k: int = 10):
    return se.ground_truth(queries_n1(spark, sf_dir, k), vectors(spark, sf_dir), n1(spark, sf_dir))


query("ground_truth_topk", ANSWER)(truth_n1)
query("prefilter_topk", ANSWER)(lambda spark, sf_dir: se.prefilter(queries_n1(spark, sf_dir), vectors(spark, sf_dir), n1(spark, sf_dir), 10))


def planned(spark, sf_dir, p=None, alpha: float = 1.4) -> pt.Partitioning:
    """The planner's partitions, each role set searching its greedy cover."""
    p = p or n1(spark, sf_dir)
    return ro.online(p, pl.plan_splits(pl.PlannerInput.collect(p), alpha).part_role(spark))


STRATEGIES = {"single": lambda s, d, p: parts(p, "rls"), "role": lambda s, d, p: parts(p, "role_part"), "user": lambda s, d, p: parts(p, "user_part"), "split": planned, "splitree": lambda s, d, p: pt.split_tree(p), "mod4": lambda s, d, p: parts(p, "mod4")}
for _name in STRATEGIES:
    @query(f"secure_topk_{_name}", ANSWER)
    def _secure(spark, sf_dir, n=_name):
        p = n1(spark, sf_dir)
        return se.secure_search(queries_n1(spark, sf_dir), vectors(spark, sf_dir), p, STRATEGIES[n](spark, sf_dir, p))


@query("secure_topk_arrow", ANSWER)
def secure_topk_arrow(spark, sf_dir):
    """Matrix products over the copies of the planned partitions."""
    p = n1(spark, sf_dir)
    part = planned(spark, sf_dir, p)
    copies = part.part_doc.join(vectors(spark, sf_dir).select("doc_id", "embedding"), "doc_id")
    return se.search_stored(copies, queries_n1(spark, sf_dir), p, part)


def flagship(spark, sf_dir):
    """Secure top-10 through the planned partitions."""
    return _secure(spark, sf_dir, "split")


@query("logical_vs_physical_result", "SELECT 'differences' AS check_name, 0::BIGINT AS violations")
def logical_vs_physical_result(spark, sf_dir):
    """Ids joined back to one vector table, against copies of vectors in partitions."""
    p = n1(spark, sf_dir)
    part, q, v = parts(p, "mod4"), queries_n1(spark, sf_dir), vectors(spark, sf_dir).select("doc_id", "embedding")
    copies = part.part_doc.join(v, "doc_id")
    rows = copies.join(se.small(se.routed_queries(q, p, part)), "part").select("query_id", "rs", "doc_id", vec.l2sq("embedding", "qvec").alias("dist"))
    physical = se.merge(se.permitted_only(rows, p), 10)
    logical = se.secure_search(q, v, p, part)
    return physical.exceptAll(logical).union(logical.exceptAll(physical)).agg(F.lit("differences").alias("check_name"), F.count("*").alias("violations"))


POST = """cand AS (SELECT DISTINCT query_id, rs, part, dist.doc_id, d FROM queries JOIN user_sets USING (user_id) JOIN route USING (rs) JOIN part_doc USING (part) JOIN dist USING (query_id, doc_id) QUALIFY row_number() OVER (PARTITION BY query_id, part ORDER BY round(d, 6), dist.doc_id) <= {ef}),
kept AS (SELECT DISTINCT query_id, doc_id, d FROM cand SEMI JOIN allowed USING (query_id, doc_id)),
got AS (SELECT query_id, doc_id FROM kept QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(d, 6), doc_id) <= 10),
recall AS (SELECT query_id, count(got.doc_id) / count(*) AS r FROM truth LEFT JOIN got USING (query_id, doc_id) GROUP BY query_id)
"""


def _post(part: str, ef: int) -> str:
    return with_(POLICIES["n1"], SETS, PARTS[part], distances(), TRUTH, POST.format(ef=ef))


@query("postfilter_exact_ef", _post("rls", 60) + "SELECT query_id, count(*) AS n_kept FROM kept GROUP BY query_id")
def postfilter_exact_ef(spark, sf_dir):
    p = n1(spark, sf_dir)
    found = se.permitted_only(sc.candidates(queries_n1(spark, sf_dir), vectors(spark, sf_dir), p, parts(p, "rls"), 60), p)
    return found.select("query_id", "doc_id").distinct().groupBy("query_id").agg(F.count("*").alias("n_kept"))


for _part in ("rls", "role_part"):
    for _ef in (20, 50, 100, 200):
        @query(f"recall_at_k_post_{_part}_{_ef}", _post(_part, _ef) + "SELECT round(avg(r), 6) AS recall FROM recall")
        def _recall(spark, sf_dir, part=_part, ef=_ef):
            p, q, v = n1(spark, sf_dir), queries_n1(spark, sf_dir), vectors(spark, sf_dir)
            truth = sc.ground_truth(q, v, p).cache()
            return sc.recall_by_depth(q, v, p, parts(p, part), truth, [ef]).select(r6("recall").alias("recall"))


@query("visited_partitions", with_(POLICIES["n1"], SETS, PARTS["mod4"], MEASURED, distances()) + "SELECT query_id, count(*) AS visited, sum(n_docs)::BIGINT AS evaluated FROM queries JOIN user_sets USING (user_id) JOIN route USING (rs) JOIN sizes USING (part) GROUP BY query_id")
def visited_partitions(spark, sf_dir):
    p = n1(spark, sf_dir)
    return se.search_stats(queries_n1(spark, sf_dir), vectors(spark, sf_dir), p, parts(p, "mod4"), 50).select("query_id", "visited", "evaluated")


@query("topk_underfull", with_(POLICIES["hand"]) + "SELECT user_id, count(DISTINCT doc_id) AS returned FROM ua JOIN pa USING (role_id) GROUP BY user_id")
def topk_underfull(spark, sf_dir):
    """k beyond what a user may see: everything permitted comes back."""
    p = g.hand_h1(spark)
    v = p.docs.select("doc_id", F.array(F.col("doc_id").cast("float"), F.lit(1.0).cast("float")).alias("embedding"))
    q = p.users.select(F.col("user_id").alias("query_id"), "user_id", F.lit(50).alias("k"), F.array(F.lit(3.0).cast("float"), F.lit(1.0).cast("float")).alias("qvec"))
    found = se.secure_search(q, v, p, pt.role_partition(p), k=50)
    return found.groupBy(F.col("query_id").alias("user_id")).agg(F.count("*").alias("returned"))


@query("ivf_label_probe", with_(POLICIES["n1"], distances()) + """, means AS (SELECT label, i, avg(embedding[i]::DOUBLE) AS m FROM embeddings, range(1, 65) t(i) GROUP BY label, i),
cd AS (SELECT query_id, label, round(sum((m - qvec[i]::DOUBLE) * (m - qvec[i]::DOUBLE)), 6) AS c FROM queries, means GROUP BY query_id, label),
probed AS (SELECT query_id, label FROM cd QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY c, label) <= 3)
SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY round(d, 6), doc_id) AS rank, doc_id, round(d, 6) AS dist FROM dist JOIN embeddings ON vec_id = doc_id JOIN probed USING (query_id, label) QUALIFY rank <= 10""".replace("\n)", ")"))
def ivf_label_probe(spark, sf_dir):
    """Lists by label, centroids the labels' means, three lists probed, no filter."""
    v = vectors(spark, sf_dir)
    rows = v.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("m"))
    centroids = rows.groupBy(F.col("label").alias("list_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "m"))), lambda s: s.m).alias("centroid"))
    asked = ix.IvfIndex().probes(queries_n1(spark, sf_dir).select("query_id", F.lit("all").alias("part"), "qvec"), centroids, 3)
    scored = v.select("doc_id", "embedding", F.col("label").alias("list_id")).join(asked, "list_id").select("query_id", "doc_id", vec.l2sq("embedding", "qvec").alias("dist"))
    return se.ranked(scored, 10).select("query_id", "rank", "doc_id", r6("dist").alias("dist"))


@query("index_choice", sql("mod4") + "SELECT part, CASE WHEN bool_and(permitted = n_docs) THEN 'hnsw' ELSE 'filtergraph' END AS kind FROM sel GROUP BY part")
def index_choice(spark, sf_dir):
    p = n1(spark, sf_dir)
    return ix.choose_index(p, parts(p, "mod4"))


def forbidden_rows(result, q, p) -> int:
    """Answers that the user of the query may not see: only what was returned is looked up."""
    asked = result.select("query_id", "doc_id").join(q.select("query_id", "user_id"), "query_id")
    return pol.can_access(p, asked).filter("allowed = 0").count()


def index_violations(spark, sf_dir, index, depth: int, floor: float):
    """Forbidden results, and whether recall falls below a floor at the depth given or, where that is too little for so many vectors, at the first double of it that reaches the floor."""
    p = n1(spark, sf_dir)
    part, q, v = parts(p, "mod4"), queries_n1(spark, sf_dir), vectors(spark, sf_dir)
    truth = sc.ground_truth(q, v, p)
    if isinstance(index, ix.ExactIndex):
        result = index.answers(v, q, p, part, depth).cache()
        recall = me.recall_at_k(result, truth).agg(F.avg("recall")).first()[0]
    else:  # graphs and lists are built once, then read by every step of the search
        path = scratch(spark)
        ix.persist(index.build(part, v), path)
        built, truth = ix.load(index, spark, path, v), truth.cache()
        result, recall = ix.deepened(lambda d: index.answers(built, q, p, part, d), truth, depth, floor, index.deepest(part))
        truth.unpersist()
    forbidden = forbidden_rows(result, q, p)
    result.unpersist()
    return violations(spark, {"forbidden": forbidden, "below_floor": recall >= floor})


for _name, _index, _depth, _floor in (("hnsw", ix.HnswIndex(), 100, 0.9), ("filtergraph", ix.FilterGraphIndex(), 32, 0.9), ("filtergraph_two_hops", ix.FilterGraphIndex(mode="two_hops", widen=1), 32, 0.9), ("ivf", ix.IvfIndex(), 8, 0.9), ("ivfpq", ix.IvfPqIndex(m=16, codes=32), 8, 0.9), ("exact", ix.ExactIndex(), 2000, 1.0)):
    query(f"{_name}_search", zeros("forbidden", "below_floor"))(lambda spark, sf_dir, i=_index, d=_depth, f=_floor: index_violations(spark, sf_dir, i, d, f))


@query("tune_ef")
def tune_ef(spark, sf_dir):
    """The depth at which the shared index reaches recall 0.95, from the model's estimate on."""
    p = n1(spark, sf_dir)
    part, q, v = parts(p, "rls"), queries_n1(spark, sf_dir).cache(), vectors(spark, sf_dir)
    truth = sc.ground_truth(q, v, p).cache()
    placed = sc.true_places(q, v, p, part, truth).cache()  # one pass over the vectors serves every depth
    s = me.system_selectivity(p, part).first()[0]
    start = RecallModel().ef_for(0.95, s, 10)
    ef, recall = se.tune_depth(0.95, start, lambda e: sc.recalls(placed, [e]).first().recall)
    return spark.createDataFrame([(float(start), ef, round(float(recall), 6))], "model_ef double, tuned_ef int, recall double")


TEXT = """tok AS (SELECT doc_id, line_no, unnest(regexp_extract_all(lower(line), '[a-z]+')) AS w FROM (SELECT doc_id, generate_subscripts(string_split(text, chr(10)), 1) AS line_no, unnest(string_split(text, chr(10))) AS line FROM documents)),
hashed AS (SELECT doc_id, line_no, (length(w) * 31 + ascii(substr(w, 1, 1)) * 7 + ascii(substr(w, length(w), 1))) % 16 AS bucket, CASE WHEN ascii(substr(w, 1, 1)) % 2 = 0 THEN 1 ELSE -1 END AS sign FROM tok),
sums AS (SELECT doc_id, line_no, bucket, sum(sign)::DOUBLE AS weight FROM hashed GROUP BY ALL)"""


def text_vectors(spark, sf_dir, d: int = 16):
    """doc_id, line_no, bucket, weight: signed counts of hashed words, one sparse vector for each line."""
    lines = read(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("i", "line"))
    words = lines.select("doc_id", (F.col("i") + 1).cast("long").alias("line_no"), F.explode(F.regexp_extract_all(F.lower("line"), F.lit("[a-z]+"), F.lit(0))).alias("w"))
    first = F.ascii(F.substring("w", 1, 1))
    bucket = (F.length("w") * 31 + first * 7 + F.ascii(F.substring("w", -1, 1))) % d
    return words.groupBy("doc_id", "line_no", bucket.cast("long").alias("bucket")).agg(F.sum(F.when(first % 2 == 0, 1).otherwise(-1)).cast("double").alias("weight"))


def line_vectors(spark, sf_dir, d: int):
    """doc_id, line_no, embedding: the vectors of `text_vectors` in full, of length 1; lines whose words cancel out have none. Texts are read as bytes, and no word is shuffled."""
    docs = read(spark, sf_dir, "documents").filter("text is not null").select("doc_id", F.lower("text").cast("binary").alias("text"))
    docs = docs.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))), "doc_id").sortWithinPartitions("doc_id")
    schema = pa.schema([("doc_id", pa.int64()), ("line_no", pa.int64()), ("embedding", pa.list_(pa.float32()))])

    def run(batches):
        rest = None  # the last document's rows, to which the next batch may add
        for b in batches:
            table = pa.Table.from_batches([b] if rest is None else [*rest.to_batches(), b])
            ids = table.column(0).to_numpy()
            last = int(np.searchsorted(ids, ids[-1])) if len(ids) else 0
            rest = table.slice(last)
            for i, j in text_pieces(table.slice(0, last)):
                yield embedded(table.slice(i, j - i))
        if rest is not None and rest.num_rows:
            yield embedded(rest)

    def text_pieces(table):
        """Rows of about TEXT_BYTES that begin and end between documents."""
        ids, ends = table.column(0).to_numpy(), np.cumsum(pc.binary_length(table.column(1)).to_numpy())
        i = 0
        while i < len(ids):
            j = min(len(ids), int(np.searchsorted(ends, (ends[i - 1] if i else 0) + TEXT_BYTES)) + 1)
            j = int(np.searchsorted(ids, ids[j - 1], "right"))
            yield i, j
            i = j

    def embedded(table):
        ids, texts = table.column(0).to_numpy(), table.column(1).to_pylist()
        # A break before each text, so that no word goes on into the next.
        text = np.frombuffer(b"\n".join([b"", *texts, b""]), np.uint8)
        letter = (text - np.uint8(97)) < 26
        edges = np.flatnonzero(letter[1:] != letter[:-1]) + 1
        begin, end = edges[::2], edges[1::2]
        first = text[begin].astype(np.int32)
        bucket = ((end - begin).astype(np.int32) * 31 + first * 7 + text[end - 1]) % d
        breaks = np.flatnonzero(text == 10)
        opens = np.searchsorted(breaks, np.r_[0, np.cumsum([len(x) + 1 for x in texts])])  # of each text, and of the end: its first line
        # Texts of one id share their lines.
        group = np.cumsum(np.r_[False, ids[1:] != ids[:-1]])
        n_lines = np.zeros(group[-1] + 1, np.int64) if len(ids) else np.zeros(0, np.int64)
        np.maximum.at(n_lines, group, np.diff(opens))
        base = np.r_[0, np.cumsum(n_lines)]
        slot = np.arange(opens[-1]) + np.repeat(base[group] - opens[:-1], np.diff(opens))  # of each line
        n_words = np.diff(np.searchsorted(begin, breaks))
        w = np.bincount(np.repeat(slot * d, n_words) + bucket, 1.0 - 2 * (first & 1), int(base[-1]) * d).reshape(-1, d)
        norm = np.sqrt((w * w).sum(axis=1))  # of whole numbers, so that their order does not matter
        kept = np.flatnonzero(norm > 0)
        own = np.repeat(np.arange(len(n_lines)), n_lines)[kept]
        flat = (w[kept] / norm[kept, None]).astype(np.float32).ravel()
        vectors = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, d), pa.int32()), pa.array(flat))
        return pa.RecordBatch.from_arrays([pa.array(ids[np.searchsorted(group, own)], pa.int64()), pa.array(kept - base[own] + 1, pa.int64()), vectors], schema=schema)

    return docs.mapInArrow(run, "doc_id bigint, line_no bigint, embedding array<float>")


@query("text_hash_embed", with_(TEXT) + "SELECT doc_id, bucket::BIGINT AS bucket, sum(weight) AS weight FROM sums GROUP BY ALL")
def text_hash_embed(spark, sf_dir):
    return text_vectors(spark, sf_dir).groupBy("doc_id", "bucket").agg(F.sum("weight").alias("weight"))


@query("secure_topk_docs", zeros("forbidden", "not_the_best_vector"))
def secure_topk_docs(spark, sf_dir):
    """Documents of several vectors (lines): the best vector of each counts."""
    p = g.natural_n3(spark, sf_dir)
    dense = text_vectors(spark, sf_dir).groupBy("doc_id", "line_no").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "weight"))).alias("m"))
    v = dense.select("doc_id", "line_no", F.transform(F.sequence(F.lit(0), F.lit(15)), lambda i: F.coalesce(F.element_at("m", i.cast("long")), F.lit(0.0)).cast("float")).alias("embedding")).cache()
    users = p.users.agg(F.min("user_id").alias("first"), F.count("*").alias("n"))  # one row
    asked = v.filter("doc_id % 20 = 0").groupBy("doc_id").agg(F.min_by("embedding", "line_no").alias("qvec"))
    q = asked.join(F.broadcast(users)).select(F.col("doc_id").alias("query_id"), (F.col("first") + F.col("doc_id") % F.col("n")).alias("user_id"), F.lit(10).alias("k"), "qvec")
    found = sc.ground_truth(q, v, p, 10, by_document=True).cache()
    bad = forbidden_rows(found, q, p)
    again = found.join(v, "doc_id").join(q.select("query_id", "qvec"), "query_id").groupBy("query_id", "doc_id", "dist").agg(F.min(vec.l2sq("embedding", "qvec")).alias("best"))
    return violations(spark, {"forbidden": bad, "not_the_best_vector": again.filter(F.abs(F.col("best") - F.col("dist")) > 1e-6).count()})


# Updates


def state_n1(spark, sf_dir) -> up.PolicyState:
    p = n1(spark, sf_dir)
    return up.PolicyState.scratch(p, mod4(p))


def digest(s: up.PolicyState):
    return s.part_doc.groupBy(big("partition_id").alias("partition_id")).agg(F.count("*").alias("n_docs"), F.sum("doc_id").alias("doc_sum"))


def after(change: str) -> str:
    """Digest of the partitions that a changed policy has when filled anew."""
    return with_(POLICIES["n1"], change) + "SELECT (role_id % 4)::BIGINT AS partition_id, count(DISTINCT doc_id) AS n_docs, sum(DISTINCT doc_id)::BIGINT AS doc_sum FROM pa2 GROUP BY 1"


@query("upd_add_user", with_(POLICIES["n1"]) + "SELECT 9000001::BIGINT AS user_id, part FROM (SELECT DISTINCT (r % 4)::VARCHAR AS part FROM (VALUES (3), (8), (102)) t(r))")
def upd_add_user(spark, sf_dir):
    new = spark.createDataFrame([(9000001, r) for r in (3, 8, 102)], "user_id long, role_id int")
    s = up.add_users(state_n1(spark, sf_dir), new)
    mine = pol.user_role_sets(s.policy).filter("user_id = 9000001").select("user_id", "rs")
    return mine.join(s.partitioning().route, "rs").select("user_id", "part")


@query("upd_drop_user", with_(POLICIES["n1"]) + "SELECT count(DISTINCT user_id) AS n_users, count(*) AS n_ua FROM ua WHERE user_id % 10 <> 0")
def upd_drop_user(spark, sf_dir):
    s = state_n1(spark, sf_dir)
    s = up.drop_users(s, s.policy.users.filter("user_id % 10 = 0"))
    return s.policy.ua.agg(F.countDistinct("user_id").alias("n_users"), F.count("*").alias("n_ua"))


def _granted(p):
    return p.docs.filter("doc_id % 9 = 0").select(F.lit(3).alias("role_id"), "doc_id").union(p.docs.filter("doc_id % 11 = 0").select(F.lit(101), "doc_id"))


def _revoked(p):
    return p.pa.filter("doc_id % 3 = 0 and role_id in (0, 4, 8, 101)").select("role_id", "doc_id")


GRANT = "pa2 AS (SELECT role_id, doc_id FROM pa UNION SELECT 3, doc_id FROM docs WHERE doc_id % 9 = 0 UNION SELECT 101, doc_id FROM docs WHERE doc_id % 11 = 0)"
REVOKE = "pa2 AS (SELECT role_id, doc_id FROM pa WHERE NOT (doc_id % 3 = 0 AND role_id IN (0, 4, 8, 101)))"


@query("upd_grant_docs", after(GRANT))
def upd_grant_docs(spark, sf_dir):
    s = state_n1(spark, sf_dir)
    return digest(up.grant_docs(s, _granted(s.policy)))


@query("upd_revoke_docs", after(REVOKE))
def upd_revoke_docs(spark, sf_dir):
    s = state_n1(spark, sf_dir)
    return digest(up.revoke_docs(s, _revoked(s.policy)))


@query("upd_drop_role", after("pa2 AS (SELECT role_id, doc_id FROM pa WHERE role_id <> 101)"))
def upd_drop_role(spark, sf_dir):
    return digest(up.drop_role(state_n1(spark, sf_dir), 101))


@query("upd_dirty_partitions", with_(POLICIES["n1"], GRANT) + "SELECT DISTINCT (coalesce(a.h, b.h))::BIGINT AS partition_id FROM (SELECT DISTINCT role_id % 4 AS h, doc_id FROM pa) a FULL JOIN (SELECT DISTINCT role_id % 4 AS h, doc_id FROM pa2) b ON a.h = b.h AND a.doc_id = b.doc_id WHERE a.h IS NULL OR b.h IS NULL")
def upd_dirty_partitions(spark, sf_dir):
    s = state_n1(spark, sf_dir)
    return up.dirty_partitions(s, up.grant_docs(s, _granted(s.policy))).select(big("partition_id").alias("partition_id"))


NEW_ROLE = "new AS (SELECT DISTINCT doc_id FROM pa WHERE doc_id % 20 = 7)"


def _new_role(p):
    pa = p.pa.filter("doc_id % 20 = 7").select(F.lit(900).alias("role_id"), "doc_id").distinct()
    ua = p.docs.sparkSession.range(9000100, 9000110).select(F.col("id").alias("user_id"), F.lit(900).alias("role_id"))
    return pa, ua


@query("upd_add_role_candidates", with_(POLICIES["n1"], NEW_ROLE) + "SELECT h::BIGINT AS partition_id, ((SELECT count(*) FROM new) - (SELECT count(*) FROM new WHERE doc_id IN (SELECT doc_id FROM pa WHERE role_id % 4 = h)))::DOUBLE AS d_storage FROM range(4) t(h) UNION ALL SELECT -1, (SELECT count(*) FROM new)")
def upd_add_role_candidates(spark, sf_dir):
    s = state_n1(spark, sf_dir)
    pa, ua = _new_role(s.policy)
    rows = [(int(o["partition_id"]), float(o["d_storage"])) for o in up.role_candidates(s, 900, pa, ua)]
    return spark.createDataFrame(rows, "partition_id long, d_storage double")


@query("upd_state_violations", zeros("grant", "revoke", "add_role", "drop_role", "uncovered"))
def upd_state_violations(spark, sf_dir):
    from aclvec.operators.routing import cover_violations

    s = state_n1(spark, sf_dir)
    n = lambda x: up.state_violations(x).first()[0]
    pa, ua = _new_role(s.policy)
    grown = up.add_role(s, 900, pa, ua)
    return violations(spark, {"grant": n(up.grant_docs(s, _granted(s.policy))), "revoke": n(up.revoke_docs(s, _revoked(s.policy))), "add_role": n(grown), "drop_role": n(up.drop_role(s, 101)), "uncovered": cover_violations(grown.policy, grown.partitioning()).first()[0]})


@query("upd_refresh_route", with_(POLICIES["n1"], "ua2 AS (SELECT user_id, role_id FROM ua WHERE user_id % 10 <> 0 UNION SELECT 9000001, unnest([3, 8, 102]))", "sets2 AS (SELECT user_id, string_agg(role_id::VARCHAR, ',' ORDER BY role_id) AS rs FROM ua2 GROUP BY user_id)") + "SELECT DISTINCT rs, (role_id % 4)::VARCHAR AS part FROM sets2 JOIN ua2 USING (user_id)")
def upd_refresh_route(spark, sf_dir):
    """The route after users went and one with a new combination of roles came: only that combination is routed anew."""
    s = state_n1(spark, sf_dir)
    new = spark.createDataFrame([(9000001, r) for r in (3, 8, 102)], "user_id long, role_id int")
    return up.refresh_route(s.partitioning().route, up.add_users(up.drop_users(s, s.policy.users.filter("user_id % 10 = 0")), new))


@query("upd_repartition_advice", "SELECT i::BIGINT AS incremental, q::BIGINT AS queries, i > 1.1 * 100 AND (i - 100) * q > 50000 AS rebuild FROM (VALUES (100), (105), (115), (150)) t(i), (VALUES (1000), (2000), (10000)) u(q)")
def upd_repartition_advice(spark, sf_dir):
    """Whether to plan anew, for states that cost more than a fresh plan of cost 100 and a rebuild of 50,000."""
    rows = [(i, q, up.repartition_advice(i, 100, 50_000, q)) for i in (100, 105, 115, 150) for q in (1000, 2000, 10_000)]
    return spark.createDataFrame(rows, "incremental long, queries long, rebuild boolean")


@query("upd_answers", zeros("differences"))
def upd_answers(spark, sf_dir):
    """Answers after grants, revocations and a dropped role in place, against the truth of the changed policy."""
    s, v, q = state_n1(spark, sf_dir), vectors(spark, sf_dir), queries_n1(spark, sf_dir)
    now = up.drop_role(up.revoke_docs(up.grant_docs(s, _granted(s.policy)), _revoked(s.policy)), 101)
    got, true = sc.secure_search(q, v, now.policy, now.partitioning()).cache(), sc.ground_truth(q, v, now.policy).cache()
    return got.exceptAll(true).union(true.exceptAll(got)).agg(F.lit("differences").alias("check_name"), F.count("*").alias("violations"))


@query("upd_vs_rebuild")
def upd_vs_rebuild(spark, sf_dir):
    """Model cost of states after 1 and 3 role insertions, over that of a fresh plan at alpha 1.5."""
    p = n1(spark, sf_dir)
    rows = []
    for n_ops in (1, 3):
        s = up.PolicyState.scratch(p, pl.plan_splits(pl.PlannerInput.collect(p), 1.5).part_role(spark))
        ua, pa = g.gen_role_insertions(p, n_ops)
        for r in range(900, 900 + n_ops):
            s = up.add_role(s, r, pa.filter(F.col("role_id") == r), ua.filter(F.col("role_id") == r))
        fresh = up.PolicyState.scratch(s.policy, pl.plan_splits(pl.PlannerInput.collect(s.policy), 1.5).part_role(spark))
        rows.append((n_ops, round(up.model_cost(s) / up.model_cost(fresh), 4)))
    return spark.createDataFrame(rows, "n_ops int, cost_ratio double")


@query("index_reload", zeros("hnsw", "filtergraph", "ivf", "ivfpq"))
def index_reload(spark, sf_dir):
    """Answers of an index that was written and read again against those of the one just built."""
    p, v = g.natural_n1(spark, sf_dir), vectors(spark, sf_dir)
    part, queries = pt.role_homes(p, mod4(p)), queries_n1(spark, sf_dir)
    differ = {}
    for name in ("hnsw", "filtergraph", "ivf", "ivfpq"):
        index, path = ix.INDEXES[name](), scratch(spark)
        built = index.build(part, v)
        if not isinstance(built, tuple):
            built = built.cache()  # graphs are built once for the writing and the search
        ix.persist(built, path)
        differ[name] = reload_differences(index, built, ix.load(index, spark, path, v), queries, p, part)
        if not isinstance(built, tuple):
            built.unpersist()
    return violations(spark, differ)


def reload_differences(index, built, again, queries, p, part, depth: int = 8) -> int:
    """Rows that one of two indexes has, or finds at a depth, and the other does not.

    A search of plain lists finds all rows of the lists that it probes, so probes and rows of
    lists are compared in place of each query's candidates, which follow from them.
    """

    def differing(a, b) -> int:
        return a.withColumn("n", F.lit(1)).union(b.withColumn("n", F.lit(-1))).groupBy(*a.columns).agg(F.sum("n").alias("n")).filter("n <> 0").count()

    if isinstance(index, ix.IvfIndex):
        asked = se.routed_queries(queries, p, part).cache()
        probes = (index.probes(asked, x[1], depth).select("query_id", "rs", "part", "list_id") for x in (built, again))
        n = differing(*probes) + differing(*(x[0].select("doc_id", "list_id", "embedding") for x in (built, again)))
        asked.unpersist()
        return n
    cols = ["query_id", "part", "doc_id", F.round("dist", 5).alias("dist")]
    return differing(*(index.search(x, queries, p, part, depth).select(*cols) for x in (built, again)))
