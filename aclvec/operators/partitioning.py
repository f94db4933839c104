"""Partitionings: the extremes, the disjoint tree from a workload, and their physical and logical forms."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aclvec.operators.policy import Policy, auth, auth_counts, auth_role_sets, doc_classes, role_sets


#: Copies that one task writes to a partition.
WRITE_ROWS = 200_000


@dataclass(frozen=True)
class Partitioning:
    """part_doc(part, doc_id): copies of documents; route(rs, part): where each role set searches. `part` is text."""

    name: str
    part_doc: DataFrame
    route: DataFrame

    def sizes(self) -> DataFrame:
        return self.part_doc.groupBy("part").agg(F.count("*").alias("n_docs"))


def single_partition(p: Policy) -> Partitioning:
    """All documents together: the basis of filtering after a search."""
    return Partitioning("rls", p.docs.select(F.lit("all").alias("part"), "doc_id"), role_sets(p).select("rs", F.lit("all").alias("part")))


def role_partition(p: Policy) -> Partitioning:
    part = F.col("role_id").cast("string").alias("part")
    return Partitioning("role_part", p.pa.select(part, "doc_id").distinct(), role_sets(p).select("rs", F.explode("role_set").alias("role_id")).select("rs", part))


def user_partition(p: Policy) -> Partitioning:
    """A partition for each distinct role set; users of the same roles share it."""
    return Partitioning("user_part", auth_role_sets(p).select(F.col("rs").alias("part"), "doc_id"), role_sets(p).select("rs", F.col("rs").alias("part")))


def per_user_partition(p: Policy) -> DataFrame:
    """part, doc_id with a partition for each single user."""
    return auth(p).select(F.col("user_id").cast("string").alias("part"), "doc_id")


def per_user_sizes(p: Policy) -> DataFrame:
    """part, n_docs of the partitions of single users, without their rows: users of one role set have as many."""
    return auth_counts(p).select(F.col("user_id").cast("string").alias("part"), "n_docs")


def role_homes(p: Policy, part_role: DataFrame, name: str = "split") -> Partitioning:
    """Partitions of whole roles: each role's documents lie in its home."""
    homes = F.broadcast(part_role.select("role_id", F.col("partition_id").cast("string").alias("part")))  # one row a role
    route = role_sets(p).select("rs", F.explode("role_set").alias("role_id")).join(homes, "role_id").select("rs", "part").distinct()
    return Partitioning(name, p.pa.join(homes, "role_id").select("part", "doc_id").distinct(), route)


def split_tree(p: Policy, min_leaf: float | None = None, max_entries: int | None = None) -> Partitioning:
    """A tree of disjoint leaves, cut by the roles that the workload's role sets ask for.

    At each leaf the role is taken that lets role sets skip most rows, weighted
    by users; a leaf stops when it is below `min_leaf` (documents / roles) or no
    cut skips anything. Cuts are chosen by sums over all access classes (taken
    by Spark beyond `max_entries`) and kept as predicates on role sets, through
    which every document goes to its leaf.
    """
    from aclvec.operators.planner import PlannerInput, leaf_sums

    data = PlannerInput.collect(p, max_entries=max_entries)
    least = min_leaf if min_leaf is not None else data.total_docs / max(1, len(data.roles))
    todo, n_leaves, cuts, columns = [0], 1, [], []
    while todo:
        at = todo.pop()
        (rows,), (n_classes,), inside, needs_in, needs_out = data.summed(data.sets, leaf_sums, columns, at)
        if rows < least or n_classes < 2:
            continue
        gain = data.weight @ ((needs_in == 0) * inside[None] + (needs_out == 0) * (rows - inside)[None])
        gain[(inside == 0) | (inside == rows)] = 0
        best = int(gain.argmax())
        if gain[best] <= 0:
            continue
        columns.append((at, best, n_leaves))
        cuts.append((at, int(data.roles[best]), n_leaves))
        todo += [at, n_leaves]
        n_leaves += 1
    at = F.lit(0)
    if cuts:
        # Cuts in the order they were made: without the role, a document goes on to the new leaf.
        made = F.array(*(F.struct(F.lit(x).alias("leaf"), F.lit(role).alias("role_id"), F.lit(new).alias("new")) for x, role, new in cuts))
        at = F.aggregate(made, at, lambda x, c: F.when((x == c["leaf"]) & ~F.array_contains("role_set", c["role_id"]), c["new"]).otherwise(x))
    placed = doc_classes(p).select("doc_id", "role_set", F.concat(F.lit("t"), at.cast("string")).alias("part"))
    held = placed.select("part", F.explode("role_set").alias("role_id")).distinct()
    route = role_sets(p).select("rs", F.explode("role_set").alias("role_id")).join(held, "role_id").select("rs", "part").distinct()
    return Partitioning("splitree", placed.select("part", "doc_id"), route)


def materialise(part: Partitioning, vectors: DataFrame, path: str, mode: str = "physical") -> None:
    """Writes a partitioning: `physical` copies vectors into directories by partition, `logical` stores ids only."""
    rows = part.part_doc
    if mode == "physical":
        rows = rows.join(vectors, "doc_id")
    elif mode != "logical":
        raise ValueError(mode)
    # A partition of any size is dealt to as many tasks as it has shards.
    sizes = part.sizes().select("part", F.ceil(F.col("n_docs") / WRITE_ROWS).cast("int").alias("n_shards"))
    rows = rows.join(sizes, "part").withColumn("shard", F.pmod(F.xxhash64(F.lit(29), "doc_id"), "n_shards")).drop("n_shards")
    rows.repartition("part", "shard").drop("shard").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("part").parquet(path)


def uncovered(p: Policy, part: Partitioning) -> DataFrame:
    """One row: permitted documents of role sets that lie in none of the routed partitions.

    Documents of one access class that lie in the same partitions count together:
    role sets meet classes and their places, never documents.
    """
    places = part.part_doc.groupBy("doc_id").agg(F.array_sort(F.collect_set("part")).alias("parts"))
    alike = doc_classes(p).join(places, "doc_id", "left").groupBy("cls", "role_set", "parts").agg(F.count("*").alias("n"))
    asked = role_sets(p).select("rs", F.explode("role_set").alias("role_id"))
    routes = part.route.groupBy("rs").agg(F.collect_set("part").alias("route"))
    may = asked.join(alike.withColumn("role_id", F.explode("role_set")), "role_id").select("rs", "cls", "parts", "n").distinct()
    missed = may.join(routes, "rs", "left").filter(~F.coalesce(F.arrays_overlap("parts", "route"), F.lit(False)))
    return missed.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("violations"))


def check_feasible(part: Partitioning, p: Policy, alpha: float) -> DataFrame:
    """check_name, violations: whole roles in one partition, role sets covered, storage within alpha."""
    n = p.docs.count()
    checks = {
        "uncovered": uncovered(p, part),
        "over_budget": part.part_doc.agg(F.when(F.count("*") > alpha * n, 1).otherwise(0).cast("long").alias("violations")),
        "empty_partition": part.route.select("part").distinct().join(part.part_doc, "part", "left_anti").agg(F.count("*").alias("violations")),
    }
    out = None
    for name, one in checks.items():
        one = one.select(F.lit(name).alias("check_name"), "violations")
        out = one if out is None else out.union(one)
    return out
