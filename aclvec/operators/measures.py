"""Costs, selectivity, memory and recall of partitionings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from aclvec.functions.models import GraphCost
from aclvec.operators.partitioning import Partitioning
from aclvec.operators.policy import Policy, doc_classes, role_sets, user_role_sets


def partition_cost(part: Partitioning, model=GraphCost(), ef: float = 40.0) -> DataFrame:
    """part, n_docs, cost of one search."""
    return part.sizes().withColumn("cost", model.cost("n_docs", ef))


def set_cost(part: Partitioning, model=GraphCost(), ef: float = 40.0) -> DataFrame:
    """rs, cost: summed over the partitions that the role set searches."""
    return part.route.join(partition_cost(part, model, ef), "part").groupBy("rs").agg(F.sum("cost").alias("cost"))


def user_cost(p: Policy, part: Partitioning, model=GraphCost(), ef: float = 40.0) -> DataFrame:
    """user_id, cost: found once a role set."""
    return user_role_sets(p).select("user_id", "rs").join(set_cost(part, model, ef), "rs").select("user_id", "cost")


def role_cost(p: Policy, part: Partitioning, homes: DataFrame, model=GraphCost(), ef: float = 40.0) -> DataFrame:
    """role_id, cost over the partitions of `homes`(role_id, part)."""
    return homes.join(partition_cost(part, model, ef), "part").groupBy("role_id").agg(F.sum("cost").alias("cost"))


def objective(p: Policy, part: Partitioning, model=GraphCost(), ef: float = 40.0, weights: DataFrame | None = None) -> DataFrame:
    """One row: the mean cost over users, or weighted by weights(user_id, weight)."""
    costs = user_cost(p, part, model, ef)
    if weights is None:
        return costs.agg(F.avg("cost").alias("cost"))
    return costs.join(weights, "user_id").agg((F.sum(F.col("cost") * F.col("weight")) / F.sum("weight")).alias("cost"))


def partition_selectivity(p: Policy, part: Partitioning) -> DataFrame:
    """rs, part, permitted, n_docs, s: the share of each searched partition that the role set may see."""
    # Role sets meet access classes and their counts in partitions, never documents.
    classes = doc_classes(p)
    placed = part.part_doc.join(classes.select("doc_id", "cls"), "doc_id").groupBy("part", "cls").agg(F.count("*").alias("n"))
    seen = classes.select("cls", "role_set").distinct().select("cls", F.explode("role_set").alias("role_id"))
    may = role_sets(p).select("rs", F.explode("role_set").alias("role_id")).join(seen, "role_id").select("rs", "cls").distinct()
    inside = part.route.join(placed, "part").join(may, ["rs", "cls"], "left_semi").groupBy("rs", "part").agg(F.sum("n").alias("permitted"))
    out = part.route.join(part.sizes(), "part").join(inside, ["rs", "part"], "left")
    return out.select("rs", "part", F.coalesce("permitted", F.lit(0)).alias("permitted"), "n_docs", (F.coalesce("permitted", F.lit(0)) / F.col("n_docs")).alias("s"))


def access_selectivity(p: Policy, part: Partitioning, mode: str = "avg_of_ratios") -> DataFrame:
    """rs, s: the mean of the ratios, or the ratio of the sums."""
    one = F.avg("s") if mode == "avg_of_ratios" else F.sum("permitted") / F.sum("n_docs")
    return partition_selectivity(p, part).groupBy("rs").agg(one.alias("s"))


def system_selectivity(p: Policy, part: Partitioning) -> DataFrame:
    """One row: the mean over users."""
    return role_sets(p).select("rs", "n_users").join(access_selectivity(p, part), "rs").agg((F.sum(F.col("s") * F.col("n_users")) / F.sum("n_users")).alias("s"))


def memory_overhead(p: Policy, part: Partitioning) -> DataFrame:
    """strategy, overhead: stored documents over all documents."""
    n = p.docs.agg(F.count("*").alias("n"))
    return part.part_doc.agg(F.count("*").alias("rows")).join(F.broadcast(n)).select(F.lit(part.name).alias("strategy"), (F.col("rows") / F.col("n")).alias("overhead"))


def physical_bytes(sizes: DataFrame, d: int = 64, m: int = 16) -> DataFrame:
    """One row: modelled bytes of graphs with copied vectors, 4 for each scalar and each of 3 m links."""
    return sizes.agg((F.sum("n_docs") * 4 * (d + 3 * m)).cast("long").alias("bytes"))


def logical_overhead(total: float, stored: float, d: int = 64, m: int = 16) -> float:
    """Bytes of one vector table and links of all copies, over those of one shared index."""
    return (total * d + 3 * m * stored) / (total * d + 3 * m * total)


def saving(memory: float, role_memory: float) -> float:
    """The share of the additional memory of partitions by role that is saved."""
    return 1 - (memory - 1) / (role_memory - 1)


def recall_at_k(result: DataFrame, truth: DataFrame) -> DataFrame:
    """query_id, recall: found true neighbours over true neighbours (fewer than k if fewer are permitted)."""
    hits = truth.select("query_id", "doc_id").join(result.select("query_id", "doc_id").distinct().withColumn("hit", F.lit(1)), ["query_id", "doc_id"], "left")
    return hits.groupBy("query_id").agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count("*")).alias("recall"))


def convexity(curve: DataFrame) -> DataFrame:
    """policy, mean second divided difference of cost along memory: larger means that memory pays off sooner; null with fewer than three points."""
    w = Window.partitionBy("policy").orderBy("memory")
    slope = (F.lead("cost").over(w) - F.col("cost")) / (F.lead("memory").over(w) - F.col("memory"))
    rows = curve.withColumn("slope", slope).withColumn("span", F.lead("memory").over(w) - F.lag("memory").over(w))
    bent = rows.withColumn("second", (F.col("slope") - F.lag("slope").over(w)) / F.col("span"))
    return bent.groupBy("policy").agg(F.avg("second").alias("bend"))


def model_accuracy(points: DataFrame) -> DataFrame:
    """One row for points(measured, estimated): n, mean absolute percentage error (of measured values that are not 0), root mean square error, rank correlation."""
    ranks = lambda c: F.rank().over(Window.orderBy(c)).cast("double")  # noqa: E731  # a few points of a curve
    rows = points.select("measured", "estimated", ranks("measured").alias("rm"), ranks("estimated").alias("re"))
    off = F.col("estimated") - F.col("measured")
    return rows.agg(F.count("*").alias("n"), F.avg(F.when(F.col("measured") != 0, F.abs(off / F.col("measured")))).alias("mape"), F.sqrt(F.avg(off * off)).alias("rmse"), F.corr("rm", "re").alias("rank_correlation"))


def split_role_cost(sizes: list[float], whole: float) -> tuple[float, float]:
    """Sum of the logs of the parts and the log of the whole."""
    import math

    return sum(math.log(s) for s in sizes), math.log(whole)
