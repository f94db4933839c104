"""Experiments that are measured on the given tables: recall by depth and rows compared, not the models' estimates.

Searches are exact scans filtered afterwards, so recall follows from places alone
and the numbers are the same on every run.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from aclvec.functions.models import fit_recall
from aclvec.functions.portable import draw
from aclvec.operators import generators as g
from aclvec.operators import measures as me
from aclvec.operators import partitioning as pt
from aclvec.operators import planner as pl
from aclvec.operators import routing as ro
from aclvec.operators import scan as sc
from aclvec.operators import search as se
from aclvec.operators.policy import doc_classes, role_sets
from aclvec.plans.catalog_parts import n1, parts
from aclvec.plans.catalog_policy import POLICY, queries_n1, workload
from aclvec.plans.catalog_search import line_vectors, planned
from aclvec.plans.policies_sql import MEASURED, PARTS, POLICIES, SETS, TRUTH, distances, with_
from aclvec.plans.registry import query, r6
from aclvec.sources.tables import read, vectors

EFS = [10, 20, 50, 100, 200, 400]


def _union(frames):
    out = None
    for one in frames:
        out = one if out is None else out.union(one)
    return out


def evaluated(q, p, part):
    """One row: mean partitions visited and mean rows compared of a query."""
    each = se.routed_queries(q, p, part).join(part.sizes(), "part").groupBy("query_id").agg(F.count("*").alias("visited"), F.sum("n_docs").alias("rows"))
    return each.agg(r6(F.avg("visited")).alias("visited"), r6(F.avg("rows")).alias("rows_compared"))


def curve(q, v, p, part, truth, efs=EFS, placed=None):
    """strategy, ef, recall, visited, rows_compared. `placed`: places of true neighbours, where a scan for several partitionings has counted them."""
    points = sc.recall_by_depth(q, v, p, part, truth, efs) if placed is None else sc.recalls(placed, efs)
    points = points.select("ef", r6("recall").alias("recall"))
    return points.join(F.broadcast(evaluated(q, p, part))).select(F.lit(part.name).alias("strategy"), "ef", "recall", "visited", "rows_compared")


def curve_sql(names) -> str:
    """The curve of partitionings that need no plan: a true neighbour is found from its best place on."""
    out = []
    for name in names:
        body = with_(POLICIES["n1"], SETS, PARTS[name], MEASURED, distances(), TRUTH)[:-1] + """, asked AS (SELECT query_id, part FROM queries JOIN user_sets USING (user_id) JOIN route USING (rs)),
placed AS (SELECT query_id, doc_id, min(place) AS place FROM (SELECT query_id, part, dist.doc_id, row_number() OVER (PARTITION BY query_id, part ORDER BY round(d, 6), dist.doc_id) AS place
  FROM asked JOIN part_doc USING (part) JOIN dist USING (query_id, doc_id)) GROUP BY query_id, doc_id),
one AS (SELECT query_id, ef, count(*) FILTER (place <= ef) / count(*) AS r FROM truth LEFT JOIN placed USING (query_id, doc_id), unnest(EFS) t(ef) GROUP BY query_id, ef),
seen AS (SELECT query_id, count(*) AS v, sum(n_docs) AS n FROM asked JOIN sizes USING (part) GROUP BY query_id)
SELECT 'NAME' AS strategy, ef::BIGINT AS ef, round(avg(r), 6) AS recall, (SELECT round(avg(v), 6) FROM seen) AS visited, (SELECT round(avg(n), 6) FROM seen) AS rows_compared FROM one GROUP BY ef""".replace("EFS", str(EFS)).replace("NAME", name)
        out.append(f"SELECT * FROM ({body})")
    return " UNION ALL ".join(out)


PLAIN = ("rls", "role_part", "user_part")


@query("exp_recall_measured", curve_sql(PLAIN))
def exp_recall_measured(spark, sf_dir):
    """Recall by depth of the shared index and of partitions by role and by role set, with the rows that each compares."""
    p, v, q = n1(spark, sf_dir), vectors(spark, sf_dir), queries_n1(spark, sf_dir)
    truth = sc.ground_truth(q, v, p).cache()
    return _union(curve(q, v, p, parts(p, x), truth) for x in PLAIN).withColumn("ef", F.col("ef").cast("long"))


@query("exp_recall_planned")
def exp_recall_planned(spark, sf_dir):
    """The same of the planned partitions, along each role set's cover."""
    p, v, q = n1(spark, sf_dir), vectors(spark, sf_dir), queries_n1(spark, sf_dir)
    return curve(q, v, p, planned(spark, sf_dir, p), sc.ground_truth(q, v, p).cache())


def memory_row(p, q, x, name):
    return me.memory_overhead(p, x).join(F.broadcast(evaluated(q, p, x))).select(F.lit(name).alias("strategy"), r6("overhead").alias("memory"), "visited", "rows_compared")


_MEMORY = """SELECT '{n}' AS strategy, round((SELECT count(*) FROM part_doc) / (SELECT count(*) FROM docs), 6) AS memory, round(avg(v), 6) AS visited, round(avg(n), 6) AS rows_compared
FROM (SELECT query_id, count(*) AS v, sum(n_docs) AS n FROM queries JOIN user_sets USING (user_id) JOIN route USING (rs) JOIN sizes USING (part) GROUP BY query_id)"""


@query("exp_memory_measured", " UNION ALL ".join("SELECT * FROM (" + with_(POLICIES["n1"], SETS, PARTS[n], MEASURED, distances()) + _MEMORY.format(n=n) + ")" for n in PLAIN))
def exp_memory_measured(spark, sf_dir):
    """Memory, partitions visited and rows compared by the shared index and by partitions by role and by role set."""
    p, q = n1(spark, sf_dir), queries_n1(spark, sf_dir)
    return _union(memory_row(p, q, parts(p, n), n) for n in PLAIN)


@query("exp_memory_planned")
def exp_memory_planned(spark, sf_dir):
    """The same along the planner's budget, over homes and over covers, and of the disjoint tree."""
    p, q = n1(spark, sf_dir), queries_n1(spark, sf_dir)
    plans = pl.plan_spectrum(pl.PlannerInput.collect(p), [1.1, 1.24, 1.4, 2.0, 3.0])
    every = {f"planner_{a}_{m}": ro.online(p, plan.part_role(spark), m) for a, plan in plans.items() for m in ("home", "greedy_count")}
    return _union(memory_row(p, q, x, n) for n, x in {**every, "splitree": pt.split_tree(p)}.items())


@query("exp_cross_fit")
def exp_cross_fit(spark, sf_dir):
    """Recall models fitted on the tree and on the two-tier policy, both held against recall measured on the tree."""
    v = vectors(spark, sf_dir)
    measured, fitted, efs = {}, {}, [10, 20, 40, 60, 80, 100, 150, 200, 300, 400]
    for name in ("tree_a", "tier_a"):
        p = POLICY[name](spark, sf_dir)
        q = workload(spark, sf_dir).withColumn("user_id", F.col("query_id") % 150)
        q = q.join(p.ua.select("user_id").distinct(), "user_id", "left_semi")
        part = parts(p, "rls")
        points = se.recall_by_depth(q, v, p, part, se.ground_truth(q, v, p), efs).collect()  # one row a depth
        s = float(me.system_selectivity(p, part).first()[0])
        measured[name] = (s, {r.ef: r.recall for r in points})
        fitted[name], _ = fit_recall(efs, [s] * len(efs), [10] * len(efs), [measured[name][1][e] for e in efs])
    s, points = measured["tree_a"]
    out = []
    for name, model in fitted.items():
        rows = spark.createDataFrame([(float(points[e]), float(model.value(e, s, 10))) for e in efs], "measured double, estimated double")
        out.append(me.model_accuracy(rows).select(F.lit(name).alias("fitted_on"), F.lit(round(model.beta, 4)).alias("beta"), F.lit(round(model.gamma, 4)).alias("gamma"), *(r6(c).alias(c) for c in ("mape", "rmse", "rank_correlation"))))
    return _union(out)


@query("exp_query_correlation")
def exp_query_correlation(spark, sf_dir):
    """Recall of the shared index for queries drawn without regard to permissions, and for vectors of the users' own documents."""
    p, v, q = n1(spark, sf_dir), vectors(spark, sf_dir), queries_n1(spark, sf_dir)
    part = parts(p, "rls")
    # The least draw, then the least id, in one number: ids lie below 2 ** 40. A document that several roles open is met again, which changes no minimum.
    low = F.when(F.col("doc_id") < 1 << 40, F.col("doc_id")).otherwise(F.raise_error(F.lit("a doc_id of 2 ** 40 or more")).cast("long"))
    pairs = q.select("query_id", "user_id").join(p.ua, "user_id").join(p.pa, "role_id")
    mine = pairs.groupBy("query_id").agg((F.min(draw(F.col("doc_id") * 1009 + F.col("query_id"), 17, 1 << 20).cast("long") * (1 << 40) + low) % (1 << 40)).alias("doc_id"))
    own = q.drop("qvec").join(mine, "query_id").join(v.select("doc_id", F.col("embedding").alias("qvec")), "doc_id").select("query_id", "user_id", "k", "qvec")
    return _union(curve(x, v, p, part, sc.ground_truth(x, v, p).cache()).withColumn("strategy", F.lit(name)) for name, x in (("independent", q), ("own_documents", own)))


@query("exp_text_corpus")
def exp_text_corpus(spark, sf_dir):
    """Documents of several hashed line vectors under the policy of sources, languages and labels: recall of documents by depth in lines; visited partitions and rows_compared count documents."""
    p, d = g.natural_n3(spark, sf_dir), 64
    p = p.but(ua=p.ua.cache(), pa=p.pa.cache())
    role_sets(p).cache(), doc_classes(p).cache()  # the operators below ask for them again and again
    n_lines = read(spark, sf_dir, "documents").agg(F.sum(F.size(F.split("text", "\n")))).first()[0] or 0
    v = sc.dealt(line_vectors(spark, sf_dir, d), n_lines).cache()
    users = p.users.agg(F.min("user_id").alias("first"), F.count("*").alias("n"))  # one row
    first = v.filter("doc_id % 20 = 0").groupBy("doc_id").agg(F.min_by("embedding", "line_no").alias("qvec"))
    q = first.join(F.broadcast(users)).select(F.col("doc_id").alias("query_id"), (F.col("first") + F.col("doc_id") % F.col("n")).alias("user_id"), F.lit(10).alias("k"), "qvec").cache()
    truth = sc.ground_truth(q, v, p, 10, by_document=True).cache()
    part = pt.role_homes(p, pl.plan_splits(pl.PlannerInput.collect(p), 1.4).part_role(spark), "planner")
    several = [parts(p, "rls"), part, parts(p, "role_part")]
    placed = sc.true_places_in_each(q, v, p, several, truth).cache()
    return _union(curve(q, v, p, x, truth, placed=placed.filter(F.col("which") == i)) for i, x in enumerate(several))
