"""Policies: natural ones over the given tables, generated ones by the portable hash, and a small one worked by hand."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.functions.portable import draw, draw_py
from aclvec.operators.policy import Policy, flatten_two_tier
from aclvec.sources.tables import read

WIDE = 1 << 20


def natural_n1(spark: SparkSession, sf_dir: str) -> Policy:
    """Vectors by nation territory and market segment; customers by nation, every third also by segment."""
    nation = read(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("role_id"), "n_regionkey")
    e = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"), "label", (F.col("vec_id") % 25).alias("b"))
    own = (F.col("label") + 10 * (F.col("doc_id") % 3)) % 25
    # Nations are a fixed dimension of 25 rows.
    everywhere = e.filter("b = 0").join(F.broadcast(nation)).select("role_id", "doc_id")
    region = e.filter("b between 1 and 5").join(F.broadcast(nation), F.col("n_regionkey") == F.col("b") - 1).select("role_id", "doc_id")
    local = e.filter("b >= 6")
    one = local.select(own.cast("int").alias("role_id"), "doc_id")
    neighbour = local.filter("doc_id % 7 = 0").select(((own + 1) % 25).cast("int").alias("role_id"), "doc_id")
    segment = local.filter("doc_id % 2 = 0").select((100 + F.floor(F.col("label") / 2)).cast("int").alias("role_id"), "doc_id")
    pa = everywhere.unionByName(region).unionByName(one).unionByName(neighbour).unionByName(segment).distinct()
    customer = read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    names = F.array(*(F.lit(s) for s in ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")))
    ua = customer.select(F.col("c_custkey").alias("user_id"), F.col("c_nationkey").cast("int").alias("role_id"))
    also = customer.filter("c_custkey % 3 = 0").select(F.col("c_custkey").alias("user_id"), (99 + F.array_position(names, F.col("c_mktsegment"))).cast("int").alias("role_id")).filter("role_id >= 100")
    return Policy(e.select("doc_id"), customer.select(F.col("c_custkey").alias("user_id")), ua.union(also), pa)


def natural_n2(spark: SparkSession, sf_dir: str) -> Policy:
    """Parts by the nation of the customers that returned many of them at a discount."""
    line = read(spark, sf_dir, "lineitem").filter("l_returnflag = 'R' and l_quantity >= 40 and l_discount >= 0.05").select("l_orderkey", "l_partkey")
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    customer = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("int").alias("role_id"))
    pa = line.join(orders, "l_orderkey").join(customer, "o_custkey").select("role_id", F.col("l_partkey").alias("doc_id")).distinct()
    docs = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("doc_id"))
    return Policy(docs, customer.select(F.col("o_custkey").alias("user_id")), customer.select(F.col("o_custkey").alias("user_id"), "role_id"), pa.join(docs, "doc_id", "left_semi").select("role_id", "doc_id"))


def natural_n3(spark: SparkSession, sf_dir: str) -> Policy:
    """Documents by source and language, curators by the quality label, moderators by the toxic label."""
    d = read(spark, sf_dir, "documents").select("doc_id", "lang", "source")
    labels = read(spark, sf_dir, "labels").select("doc_id", "quality", "toxic")
    langs = F.array(*(F.lit(x) for x in ("de", "en", "es", "fr")))
    by_source = d.select(F.substring("source", 4, 10).cast("int").alias("role_id"), "doc_id")
    by_lang = d.select((99 + F.array_position(langs, F.col("lang"))).cast("int").alias("role_id"), "doc_id").filter("role_id >= 100")
    curated = labels.filter("quality = 1").select(F.lit(200).alias("role_id"), "doc_id")
    moderated = labels.filter("toxic = 1").select(F.lit(201).alias("role_id"), "doc_id")
    pa = by_source.union(by_lang).union(curated).union(moderated).distinct()
    u = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"))
    ua = u.select("user_id", (F.col("user_id") % 20).cast("int").alias("role_id"))
    ua = ua.union(u.filter("user_id % 4 = 0").select("user_id", (100 + F.floor(F.col("user_id") / 4) % 4).cast("int")))
    ua = ua.union(u.filter("user_id % 50 = 0").select("user_id", F.lit(200))).union(u.filter("user_id % 75 = 0").select("user_id", F.lit(201)))
    return Policy(d.select("doc_id"), u, ua, pa.join(d.select("doc_id"), "doc_id", "left_semi").select("role_id", "doc_id"))


def hand_h1(spark: SparkSession, sf_dir: str = "") -> Policy:
    """Twelve documents, four roles, six users; document 12 belongs to no role."""
    held = {1: range(1, 7), 2: range(5, 9), 3: range(8, 11), 4: range(9, 12)}
    users = {1: [1], 2: [2], 3: [3], 4: [4], 5: [1, 3], 6: [3, 4]}
    pa = spark.createDataFrame([(r, d) for r, ds in held.items() for d in ds], "role_id int, doc_id long")
    ua = spark.createDataFrame([(u, r) for u, rs in users.items() for r in rs], "user_id long, role_id int")
    return Policy(spark.range(1, 13).withColumnRenamed("id", "doc_id"), spark.range(1, 7).withColumnRenamed("id", "user_id"), ua, pa)


def tabled_h1(spark: SparkSession, sf_dir: str) -> Policy:
    """The policy of `hand_h1` on given tables: parts fall into its twelve documents and customers into its six users, by their keys."""
    held = spark.createDataFrame([(1, 1, 6), (2, 5, 8), (3, 8, 10), (4, 9, 11)], "role_id int, low int, high int")
    given = spark.createDataFrame([(1, 1), (2, 2), (3, 3), (4, 4), (5, 1), (5, 3), (6, 3), (6, 4)], "u int, role_id int")
    docs = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("doc_id"))
    users = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"))
    pa = docs.join(F.broadcast(held), (F.col("doc_id") % 12 + 1).between(F.col("low"), F.col("high"))).select("role_id", "doc_id")
    return Policy(docs, users, users.join(F.broadcast(given), F.col("user_id") % 6 + 1 == F.col("u")).select("user_id", "role_id"), pa)


def drawn_docs(roles: DataFrame, docs: DataFrame, n_docs: int, m_p: int, size_dist: str, salt: int) -> DataFrame:
    """role_id, doc_id: each role draws 1 .. m_p documents (or m_p, if `full`) by the hash; what it draws twice counts once."""
    m = F.lit(m_p) if size_dist == "full" else draw("role_id", salt, m_p) + 1
    picks = roles.select("role_id", F.explode(F.sequence(F.lit(1), m.cast("int"))).alias("i"))
    x = F.col("role_id").cast("long") * 1000003 + F.col("i")
    idx = (draw(x, salt + 1, WIDE) * WIDE + draw(x, salt + 2, WIDE)) % n_docs
    return picks.select("role_id", idx.alias("doc_id")).distinct().join(docs, "doc_id", "left_semi").select("role_id", "doc_id")


def drawn_roles(users: DataFrame, n_roles: int, m_r: int, salt: int) -> DataFrame:
    """user_id, role_id: each user draws 1 .. m_r roles."""
    picks = users.select("user_id", F.explode(F.sequence(F.lit(1), (draw("user_id", salt, m_r) + 1).cast("int"))).alias("i"))
    return picks.select("user_id", draw(F.col("user_id") * 1009 + F.col("i"), salt + 1, n_roles).cast("int").alias("role_id")).distinct()


def role_ids(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").cast("int").alias("role_id"))


def gen_uniform(spark: SparkSession, docs: DataFrame, n_docs: int, n_users: int = 1000, n_roles: int = 100, m_r: int = 2, m_p_factor: int = 5, size_dist: str = "uniform") -> Policy:
    """Roles draw documents, users draw roles, without structure. Documents are 0 .. n_docs-1."""
    users = spark.range(n_users).withColumnRenamed("id", "user_id")
    pa = drawn_docs(role_ids(spark, n_roles), docs, n_docs, max(1, n_docs * m_p_factor // n_roles), size_dist, 3)
    return Policy(docs, users, drawn_roles(users, n_roles, m_r, 13), pa)


def tree_parents(n_roles: int, height: int = 4, b0: int = 3, b1: int = 4) -> list[int | None]:
    """Parents of a tree grown breadth first: children per node by the hash, until the pool of roles or the height is used up."""
    parents: list[int | None] = [None]
    depth, at = [0], 0
    while at < len(parents) and len(parents) < n_roles:
        if depth[at] < height:
            for _ in range(b0 + draw_py(at, 21, b1 - b0 + 1)):
                if len(parents) < n_roles:
                    parents.append(at)
                    depth.append(depth[at] + 1)
        at += 1
    return parents


def tree_ancestors(parents: list[int | None]) -> list[tuple[int, int]]:
    """(role, itself or an ancestor); as many rows as roles x height."""
    out = []
    for r in range(len(parents)):
        a: int | None = r
        while a is not None:
            out.append((r, a))
            a = parents[a]
    return out


def gen_tree(spark: SparkSession, docs: DataFrame, n_docs: int, n_users: int = 1000, n_roles: int = 100, height: int = 4, b0: int = 3, b1: int = 4, bounds: list[float] | None = None) -> Policy:
    """A tree of roles; each owns a block of documents and sees those of its ancestors. `bounds`: ends of the blocks as shares of the documents."""
    parents = tree_parents(n_roles, height, b0, b1)
    n = len(parents)
    anc = F.broadcast(spark.createDataFrame(tree_ancestors(parents), "role_id int, block int"))  # roles x height rows
    if bounds is None:
        block = F.floor(F.col("doc_id") * n / n_docs).cast("int")
    else:
        block = sum((F.when(F.col("doc_id") >= math.floor(e * n_docs), 1).otherwise(0) for e in bounds[:-1]), F.lit(0))
    pa = docs.withColumn("block", block).join(anc, "block").select("role_id", "doc_id")
    users = spark.range(n_users).withColumnRenamed("id", "user_id")
    return Policy(docs, users, users.select("user_id", (1 + F.col("user_id") % max(1, n - 1)).cast("int").alias("role_id")), pa)


def poisson(u: float, lam: float) -> int:
    """The inverse of the Poisson distribution function."""
    k, p = 0, math.exp(-lam)
    total = p
    while total < u and k < 1000:
        k += 1
        p *= lam / k
        total += p
    return k


def tree_bounds(n_roles: int, target: float, lam: float = 20.0, height: int = 4, b0: int = 3, b1: int = 4) -> list[float]:
    """Block ends with Poisson sizes, upper nodes weighted so that users of the tree see `target` of the documents on average."""
    parents = tree_parents(n_roles, height, b0, b1)
    anc = tree_ancestors(parents)
    depth = [sum(1 for r, _ in anc if r == i) - 1 for i in range(len(parents))]
    sizes = [1 + poisson((draw_py(i, 51, 100_000) + 0.5) / 100_000, lam) for i in range(len(parents))]

    def shares(power: float) -> list[float]:
        w = [s * math.exp(-power * d) for s, d in zip(sizes, depth, strict=True)]
        return [x / sum(w) for x in w]

    def mean(power: float) -> float:
        w = shares(power)
        return sum(w[a] for r, a in anc if r > 0) / max(1, len(parents) - 1)

    low, high = -5.0, 8.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if mean(mid) < target else (low, mid)
    out, total = [], 0.0
    for x in shares((low + high) / 2):
        total += x
        out.append(total)
    return out


def gen_two_tier(spark: SparkSession, docs: DataFrame, n_docs: int, n_users: int = 1000, n_fr: int = 40, n_br: int = 100, m_fr: int = 3, m_br: int = 3, m_p_divisor: int = 25, size_dist: str = "full") -> Policy:
    """Functional roles draw documents, business roles draw functional roles, users draw business roles."""
    func = drawn_docs(role_ids(spark, n_fr), docs, n_docs, max(1, n_docs // m_p_divisor), size_dist, 41)
    biz = drawn_roles(role_ids(spark, n_br).select(F.col("role_id").cast("long").alias("user_id")), n_fr, m_fr, 31).select(F.col("user_id").cast("int").alias("role_id"), F.col("role_id").alias("func_id"))
    users = spark.range(n_users).withColumnRenamed("id", "user_id")
    return Policy(docs, users, drawn_roles(users, n_br, m_br, 33), flatten_two_tier(func, biz))


def gen_queries(vectors: DataFrame, users: DataFrame, n: int, k: int = 10) -> DataFrame:
    """query_id, user_id, k, qvec: stored vectors and users chosen by the hash."""
    picked = vectors.select("vec_id", "embedding", draw("vec_id", 11, WIDE).alias("h")).orderBy("h", "vec_id").limit(n)
    users = users.select("user_id", draw("user_id", 13, WIDE).alias("h")).orderBy("h", "user_id").limit(n)
    rank = lambda df, c: df.withColumn("query_id", rank_of(F.col("h"), F.col(c)))
    q = rank(picked, "vec_id").select("query_id", F.col("embedding").alias("qvec"), F.col("vec_id").alias("q_vec_id"))
    u = rank(users, "user_id").select("query_id", "user_id")
    return q.join(u, "query_id").withColumn("k", F.lit(k))


def rank_of(h: Column, key: Column) -> Column:
    """The place of a row among the few that were picked."""
    from pyspark.sql.window import Window

    return F.row_number().over(Window.orderBy(h, key)).cast("long")


def gen_role_insertions(p: Policy, n_ops: int, first_role: int = 900, user_share: float = 0.01) -> tuple[DataFrame, DataFrame]:
    """ua and pa rows of new roles, each with about a twentieth of the documents that some role holds, and new users."""
    spark = p.docs.sparkSession
    roles = spark.range(n_ops).select((F.col("id") + first_role).cast("int").alias("role_id"))
    held = p.pa.select("doc_id").distinct()
    pa = held.join(F.broadcast(roles)).filter(draw(F.col("doc_id") * 1009 + F.col("role_id"), 61, 1000) < 50).select("role_id", "doc_id")  # n_ops rows
    per_role = max(1, int(p.users.count() * user_share))
    ua = roles.select(F.explode(F.sequence(F.lit(0), F.lit(per_role - 1))).alias("i"), "role_id").select((10_000_000 + (F.col("role_id") - first_role) * per_role + F.col("i")).cast("long").alias("user_id"), "role_id")
    return ua, pa


def gen_role_deletions(p: Policy, n_ops: int) -> DataFrame:
    """role_id of the roles to drop: the first by the hash."""
    return p.roles.select("role_id", draw("role_id", 67, WIDE).alias("h")).orderBy("h", "role_id").limit(n_ops).select("role_id")
