"""Policy changes applied to a partitioned state: only what a change touches is rewritten."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aclvec.functions.models import GraphCost
from aclvec.operators.measures import objective
from aclvec.operators.partitioning import Partitioning, role_homes
from aclvec.operators.planner import PlannerInput, State, state_of
from aclvec.operators.policy import Policy, role_sets


@dataclass(frozen=True)
class PolicyState:
    """A policy with the homes of its roles: part_role(partition_id, role_id); part_doc(partition_id, doc_id)."""

    policy: Policy
    part_role: DataFrame
    part_doc: DataFrame

    @classmethod
    def scratch(cls, p: Policy, part_role: DataFrame) -> PolicyState:
        """Partitions filled anew from the policy."""
        homes = F.broadcast(part_role)  # one row a role
        return cls(p, part_role, p.pa.join(homes, "role_id").select("partition_id", "doc_id").distinct())

    def partitioning(self) -> Partitioning:
        out = role_homes(self.policy, self.part_role)
        return Partitioning("state", self.part_doc.select(F.col("partition_id").cast("string").alias("part"), "doc_id"), out.route)


def add_users(s: PolicyState, ua: DataFrame) -> PolicyState:
    """New users of existing roles: routing follows from the edges, partitions stay."""
    users = s.policy.users.union(ua.select("user_id")).distinct()
    return replace(s, policy=s.policy.but(users=users, ua=s.policy.ua.union(ua.select("user_id", "role_id")).distinct()))


def drop_users(s: PolicyState, users: DataFrame) -> PolicyState:
    return replace(s, policy=s.policy.but(users=s.policy.users.join(users, "user_id", "left_anti"), ua=s.policy.ua.join(users, "user_id", "left_anti")))


def grant_docs(s: PolicyState, pa: DataFrame) -> PolicyState:
    """Documents for roles go into the homes of those roles."""
    new = pa.join(F.broadcast(s.part_role), "role_id").select("partition_id", "doc_id")
    return replace(s, policy=s.policy.but(pa=s.policy.pa.union(pa.select("role_id", "doc_id")).distinct()), part_doc=s.part_doc.union(new).distinct())


def revoke_docs(s: PolicyState, pa: DataFrame) -> PolicyState:
    """Documents taken from roles leave the home, unless another role there still sees them."""
    left = s.policy.pa.join(pa.select("role_id", "doc_id"), ["role_id", "doc_id"], "left_anti")
    homes = F.broadcast(s.part_role)
    touched = pa.join(homes, "role_id").select("partition_id", "doc_id").distinct()
    still = left.join(homes, "role_id").select("partition_id", "doc_id")
    gone = touched.join(still, ["partition_id", "doc_id"], "left_anti")
    return replace(s, policy=s.policy.but(pa=left), part_doc=s.part_doc.join(gone, ["partition_id", "doc_id"], "left_anti"))


def role_candidates(s: PolicyState, role_id: int, pa: DataFrame, ua: DataFrame, **how) -> list[dict]:
    """For every partition and a new one (-1): storage added and mean user cost, if the role went there."""
    p = s.policy.but(pa=s.policy.pa.union(pa.select("role_id", "doc_id")), ua=s.policy.ua.union(ua.select("user_id", "role_id")), users=s.policy.users.union(ua.select("user_id")).distinct())
    data = PlannerInput.collect(p)
    homes = {r.role_id: r.partition_id for r in s.part_role.collect()}
    before = sum(state_of(data, {**homes, role_id: -1}, **how).size) - float(pa.count())
    out = []
    for target in [*sorted(set(homes.values())), -1]:
        state = state_of(data, {**homes, role_id: target}, **how)
        c_r, c_u, sbar, ef = state.now()
        out.append({"partition_id": target, "d_storage": sum(state.size) - before, "c_r": c_r, "c_u": c_u})
    return out


def add_role(s: PolicyState, role_id: int, pa: DataFrame, ua: DataFrame, **how) -> PolicyState:
    """A new role goes where it costs least per storage: the least user cost, storage weighed in."""
    options = role_candidates(s, role_id, pa, ua, **how)
    base = max(o["c_u"] for o in options)
    best = max(options, key=lambda o: ((1, base - o["c_u"]) if o["d_storage"] <= 0 else (0, (base - o["c_u"]) / o["d_storage"]), -o["partition_id"]))
    target = best["partition_id"] if best["partition_id"] >= 0 else max(o["partition_id"] for o in options) + 1
    spark = s.policy.docs.sparkSession
    part_role = s.part_role.union(spark.createDataFrame([(target, role_id)], "partition_id int, role_id int"))
    grown = add_users(replace(s, part_role=part_role), ua)
    return grant_docs(grown, pa)


def drop_role(s: PolicyState, role_id: int) -> PolicyState:
    """The role's own documents leave its home; a partition without roles is gone."""
    mine = s.policy.pa.filter(F.col("role_id") == role_id)
    out = revoke_docs(s, mine)
    return replace(out, part_role=s.part_role.filter(F.col("role_id") != role_id), policy=out.policy.but(ua=s.policy.ua.filter(F.col("role_id") != role_id)))


def refresh_route(route: DataFrame, s: PolicyState) -> DataFrame:
    """The route after changes of users: rows of role sets still held stay, only sets that are new are routed."""
    sets = role_sets(s.policy).select("rs", "role_set")
    homes = F.broadcast(s.part_role.select("role_id", F.col("partition_id").cast("string").alias("part")))  # one row a role
    new = sets.join(route.select("rs").distinct(), "rs", "left_anti").select("rs", F.explode("role_set").alias("role_id"))
    return route.join(sets, "rs", "left_semi").select("rs", "part").union(new.join(homes, "role_id").select("rs", "part").distinct())


def dirty_partitions(before: PolicyState, after: PolicyState) -> DataFrame:
    """partition_id of the partitions whose documents changed: only their indexes are built again."""
    gone = before.part_doc.exceptAll(after.part_doc)
    new = after.part_doc.exceptAll(before.part_doc)
    return gone.union(new).select("partition_id").distinct()


def state_violations(s: PolicyState) -> DataFrame:
    """One row: differences between the state's partitions and ones filled anew."""
    anew = PolicyState.scratch(s.policy, s.part_role).part_doc
    return s.part_doc.exceptAll(anew).union(anew.exceptAll(s.part_doc)).agg(F.count("*").alias("violations"))


def model_cost(s: PolicyState, **how) -> float:
    """Mean user cost of the state by the model."""
    data = PlannerInput.collect(s.policy)
    homes = {r.role_id: r.partition_id for r in s.part_role.collect()}
    return (state_of(data, {r: homes[r] for r in data.roles.tolist()}, **how) if homes else State(data, **how)).now()[1]


def repartition_advice(incremental_cost: float, fresh_cost: float, rebuild_cost: float, expected_queries: float, tau: float = 0.1) -> bool:
    """Rebuild if the state costs more than (1 + tau) of a fresh plan and the queries to come repay the rebuild."""
    return incremental_cost > (1 + tau) * fresh_cost and (incremental_cost - fresh_cost) * expected_queries > rebuild_cost


def mean_cost(s: PolicyState, ef: float = 40.0, model=GraphCost()) -> DataFrame:
    return objective(s.policy, s.partitioning(), model, ef)
