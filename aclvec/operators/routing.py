"""Where each role set searches: sets of partitions that cover its documents, found once and looked up by key."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aclvec.operators.partitioning import Partitioning, role_homes, uncovered
from aclvec.operators.policy import Policy, doc_classes, role_sets, user_role_sets


def partitions_of_role(p: Policy, part: Partitioning) -> DataFrame:
    """role_id, part: partitions that hold any document of the role."""
    return p.pa.join(part.part_doc, "doc_id").select("role_id", "part").distinct()


def partitions_of_user(p: Policy, part: Partitioning) -> DataFrame:
    """user_id, part: the union over the user's roles."""
    return p.ua.join(partitions_of_role(p, part), "role_id").select("user_id", "part").distinct()


def cover_items(p: Policy, part: Partitioning, level: str = "roleset") -> DataFrame:
    """rs, part, cls, n_docs, size: classes that a question may see and a partition holds. `level='role'`: each role alone."""
    asks = role_sets(p).select("rs", F.explode("role_set").alias("role_id")) if level == "roleset" else p.roles.select(F.col("role_id").cast("string").alias("rs"), "role_id")
    classes = doc_classes(p)
    placed = part.part_doc.join(classes.select("doc_id", "cls"), "doc_id").groupBy("part", "cls").agg(F.count("*").alias("n_docs"))
    seen = classes.select("cls", "role_set").distinct().select("cls", F.explode("role_set").alias("role_id"))
    may = asks.join(seen, "role_id").select("rs", "cls").distinct()
    return may.join(placed, "cls").join(part.sizes().withColumnRenamed("n_docs", "size"), "part").select("rs", "part", "cls", "n_docs", "size")


def _greedy(rows: pd.DataFrame, ratio: bool) -> list[str]:
    """Partition after partition: most uncovered documents (or most per size), then smaller, then smaller name."""
    left, chosen = dict(zip(rows["cls"], rows["n_docs"], strict=True)), []
    held = {k: (int(g["size"].iloc[0]), set(g["cls"])) for k, g in rows.groupby("part")}
    while left:
        def key(k):
            size, classes = held[k]
            new = sum(left.get(c, 0) for c in classes)
            return (new / size if ratio else new, -size)

        best = max(sorted(held), key=key)
        chosen.append(best)
        for c in held.pop(best)[1]:
            left.pop(c, None)
    return chosen


def _exact(rows: pd.DataFrame) -> list[str]:
    """The covering set of least summed log size, by branch and bound from the greedy one."""
    cost = {k: math.log(max(int(g["size"].iloc[0]), 2)) for k, g in rows.groupby("part")}
    # Classes that the same partitions hold are one need.
    needs = {frozenset(g["part"]) for _, g in rows.groupby("cls")}
    best = [sorted(_greedy(rows, ratio)) for ratio in (False, True)]
    best = min(best, key=lambda x: sum(cost[k] for k in x))
    least = sum(cost[k] for k in best)

    def search(needs: set[frozenset], chosen: list[str], spent: float) -> None:
        nonlocal best, least
        if not needs:
            if spent < least - 1e-12:
                best, least = sorted(chosen), spent
            return
        # Every need costs its cheapest partition at least; one without any can't be met.
        if spent + max(min((cost[k] for k in x), default=math.inf) for x in needs) >= least - 1e-12:
            return
        for k in sorted(min(needs, key=lambda x: (len(x), sorted(x))), key=lambda k: (cost[k], k)):
            search({x for x in needs if k not in x}, [*chosen, k], spent + cost[k])
            needs = {x - {k} for x in needs}  # covers with k are done

    search(needs, [], 0.0)
    return best


def cover(p: Policy, part: Partitioning, method: str = "greedy_count", level: str = "roleset") -> DataFrame:
    """rs, part, pick: covering partitions of each role set in the order of choice. A group holds classes x partitions of one role set.

    Methods: greedy_count, greedy_ratio, exact (time may grow exponentially with partitions), home (the partitioning's own route).
    """
    if method == "home":
        return part.route.withColumn("pick", F.lit(0))
    choose = {"greedy_count": lambda r: _greedy(r, False), "greedy_ratio": lambda r: _greedy(r, True), "exact": _exact}[method]

    def run(key, rows):
        chosen = choose(rows)
        return pd.DataFrame({"rs": key[0], "part": chosen, "pick": range(len(chosen))})

    return cover_items(p, part, level).groupBy("rs").applyInPandas(run, "rs string, part string, pick int")


def routed(part: Partitioning, route: DataFrame) -> Partitioning:
    return Partitioning(part.name, part.part_doc, route.select("rs", "part"))


def online(p: Policy, part_role: DataFrame, method: str = "greedy_count", name: str = "split") -> Partitioning:
    """Partitions of whole roles, searched along the cover of each role set; method `home` searches all its roles' homes."""
    part = role_homes(p, part_role, name)
    return part if method == "home" else routed(part, cover(p, part, method))


def first_pick(p: Policy, part: Partitioning) -> DataFrame:
    """rs, part: the first choice of the greedy cover, as plain aggregation."""
    held = cover_items(p, part).groupBy("rs", "part", "size").agg(F.sum("n_docs").alias("new"))
    return held.groupBy("rs").agg(F.min_by("part", F.struct(-F.col("new"), "size", "part")).alias("part"))


def routing_table(p: Policy, part: Partitioning, key: str = "roleset") -> DataFrame:
    """The lookup table: rs or user_id with its partitions."""
    table = part.route.groupBy("rs").agg(F.array_sort(F.collect_set("part")).alias("parts"))
    return table if key == "roleset" else user_role_sets(p).select("user_id", "rs").join(table, "rs").select("user_id", "parts")


def routing_bytes(table: DataFrame) -> DataFrame:
    """One row: entries and bytes, at 8 for a key and 4 for a partition id."""
    return table.agg(F.count("*").alias("entries"), F.sum(8 + 4 * F.size("parts")).cast("long").alias("bytes"))


def cover_violations(p: Policy, part: Partitioning) -> DataFrame:
    """One row: permitted documents of role sets that lie in none of the routed partitions."""
    return uncovered(p, part)
