"""The experiments at the published sizes of users and roles, over the documents of the given tables.

What needs no plan (the shared index, partitions by role and by role set) is
recomputed by SQL: its memory, selectivity, depth, model cost and rows visited.
Planned partitions have no SQL; beside their figures stand claims, the published
orders and directions, as counts of violations. Times are the bench's.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from aclvec.functions.models import FilterGraphCost, GraphCost, RecallModel, fit_recall
from aclvec.operators import generators as g
from aclvec.operators import partitioning as pt
from aclvec.operators import planner as pl
from aclvec.operators import policy as pol
from aclvec.operators import routing as ro
from aclvec.operators import updates as up
from aclvec.operators.measures import logical_overhead, partition_selectivity, saving
from aclvec.plans.policies_sql import MEASURED, PARTS, SETS, TEXTS, tree, two_tier, uniform, with_
from aclvec.plans.registry import query, r6, violations, zeros
from aclvec.sources.tables import read

USERS, ROLES = 1000, 100
SELECTIVITIES = (0.04, 0.06, 0.14, 0.24)
MAKE = {
    "tree_a": (g.gen_tree, {}), "uni_a": (g.gen_uniform, {}), "tier_a": (g.gen_two_tier, {}), "tier_b": (g.gen_two_tier, {"m_br": 9}),
    "uni_s": (g.gen_uniform, {"m_r": 1, "m_p_factor": 9}), "tier_s": (g.gen_two_tier, {"m_br": 1}),
    **{f"tree_{t}": (g.gen_tree, {"bounds": g.tree_bounds(ROLES, t)}) for t in SELECTIVITIES},
}
SAID = {
    "tree_a": tree(USERS, ROLES, docs=TEXTS), "uni_a": uniform(USERS, ROLES, 2, 5, docs=TEXTS), "uni_s": uniform(USERS, ROLES, 1, 9, docs=TEXTS),
    **{n: two_tier(USERS, 40, 100, 3, m, docs=TEXTS) for n, m in (("tier_a", 3), ("tier_b", 9), ("tier_s", 1))},
    **{f"tree_{t}": tree(USERS, ROLES, docs=TEXTS, bounds=g.tree_bounds(ROLES, t)) for t in SELECTIVITIES},
}
#: Mean selectivity and memory by role and by role set.
PUBLISHED = {"tree_a": (0.036, 3.5, 3.5), "uni_a": (0.054, 3.8, 74.9), "tier_a": (0.128, 7.0, 134.0), "tier_b": (0.285, 7.0, 408.0)}
ALPHAS = [1.1, 1.24, 1.4, 1.9, 3.0]
B = 20.0


def policy(spark, sf_dir, name: str) -> pol.Policy:
    """A generated policy over `documents`, whose ids have no gaps."""
    docs = read(spark, sf_dir, "documents").select("doc_id")
    make, how = MAKE[name]
    return make(spark, docs, docs.count(), **how)


def data_of(spark, sf_dir, name: str) -> pl.PlannerInput:
    return pl.PlannerInput.collect(policy(spark, sf_dir, name))


def homes(found: pl.Plan) -> dict[int, int]:
    return dict(zip(found.roles, found.home, strict=True))


def state_for(data, found: pl.Plan, **how) -> pl.State:
    return pl.state_of(data, homes(found), **how) if found.n_partitions > 1 else pl.State(data, **how)


def role_state(data, **how) -> pl.State:
    """A partition for each role."""
    return pl.state_of(data, {int(r): i for i, r in enumerate(data.roles)}, **how)


def visited(state: pl.State) -> float:
    """Mean rows of the partitions that a user's query visits: distances of an exact search."""
    total = (np.asarray(state.visits, float)[:, : state.n_sets] * np.asarray(state.size)[:, None]).sum(axis=0)
    return float((total * state.weight).sum())


COLUMNS = "policy string, strategy string, k double, target double, memory double, partitions long, selectivity double, ef double, cost double, rows_visited double"


def told(name: str, strategy: str, state: pl.State) -> tuple:
    _, cost, sbar, ef = state.now()
    return (name, strategy, float(state.k), float(state.target), round(sum(state.size) / state.data.total_docs, 6), len(state.size), round(sbar, 6), round(ef, 4), round(cost, 4), round(visited(state), 4))


def by_user(name: str, data, k: float = 10.0, target: float = 0.95) -> tuple:
    """A partition for each role set: everything in it is permitted."""
    sizes = data.summed(data.sets, pl.part_sums, data.sets.T)[0]
    w, ef = data.weight / data.weight.sum(), RecallModel().ef_for(target, 1.0, k)
    return (name, "user_part", k, target, round(float(sizes.sum() / data.total_docs), 6), len(sizes), 1.0, round(ef, 4), round(float((GraphCost().value(sizes, ef) * w).sum()), 4), round(float((sizes * w).sum()), 4))


def extremes(spark, sf_dir, settings):
    """The shared index, partitions by role and by role set, for each (policy, k, target)."""
    rows, known = [], {}
    for name, k, target in settings:
        data = known[name] = known.get(name) or data_of(spark, sf_dir, name)
        rows += [told(name, "rls", pl.State(data, k=k, target=target)), told(name, "role_part", role_state(data, k=k, target=target)), by_user(name, data, k, target)]
    return spark.createDataFrame(rows, COLUMNS)


def extremes_sql(settings) -> str:
    out = []
    for name, k, target in settings:
        reach = RecallModel().reach(target)
        for part in ("rls", "role_part", "user_part"):
            body = with_(SAID[name], SETS, PARTS[part], MEASURED)[:-1] + f""", x AS (SELECT rs, avg(s) AS s, sum(ln(greatest(n_docs, 2))) AS logs, sum(n_docs) AS n FROM sel GROUP BY rs),
y AS (SELECT sum(s * n_users) / sum(n_users) AS s, sum(logs * n_users) / sum(n_users) AS logs, sum(n * n_users) / sum(n_users) AS n FROM x JOIN sets USING (rs))
SELECT '{name}' AS policy, '{part}' AS strategy, {k}::DOUBLE AS k, {target}::DOUBLE AS target, round((SELECT sum(n_docs) FROM sizes) / (SELECT count(*) FROM docs), 6) AS memory, (SELECT count(*) FROM sizes) AS partitions,
  round(s, 6) AS selectivity, round({k}::DOUBLE * {reach!r}::DOUBLE / s, 4) AS ef, round(logs * ({k}::DOUBLE * {reach!r}::DOUBLE / s + {B}), 4) AS cost, round(n, 4) AS rows_visited FROM y"""
            out.append(f"SELECT * FROM ({body})")
    return " UNION ALL ".join(out)


SETTINGS = {
    "exp_memory_latency": [(n, 10.0, 0.95) for n in PUBLISHED],
    "exp_recall_latency": [("tree_a", 10.0, t) for t in (0.8, 0.9, 0.95, 0.97)],
    "exp_k": [("tree_a", k, 0.95) for k in (10.0, 30.0, 60.0, 100.0)],
    "exp_selectivity": [(f"tree_{t}", 10.0, 0.95) for t in SELECTIVITIES],
    "exp_sharing": [(n, 10.0, 0.95) for n in ("tree_0.06", "tier_s", "uni_s")],
}
for _name, _settings in SETTINGS.items():
    query(_name, extremes_sql(_settings))(lambda spark, sf_dir, s=_settings: extremes(spark, sf_dir, s))


def planned_rows(spark, sf_dir, settings, alphas):
    """Along the budget: the planner's partitions, each role set visiting its homes."""
    rows = []
    for name, k, target in settings:
        data = data_of(spark, sf_dir, name)
        for alpha, found in pl.plan_spectrum(data, alphas, k=k, target=target).items():
            rows.append(told(name, f"planner_{alpha}", state_for(data, found, k=k, target=target)))
    return spark.createDataFrame(rows, COLUMNS)


for _name, _settings in SETTINGS.items():
    query(f"{_name}_planned")(lambda spark, sf_dir, s=_settings: planned_rows(spark, sf_dir, s, ALPHAS))


def gains(data, alpha: float, **how) -> tuple[float, float]:
    """The planner's speedup over the shared index by the model, and its memory."""
    found = pl.plan_splits(data, alpha, **how)
    return pl.State(data, **how).now()[1] / state_for(data, found, **how).now()[1], found.memory


@query("exp_claims", zeros("budget_exceeded", "cost_rises_with_memory", "slower_than_shared", "order_at_equal_recall", "gain_falls_with_k", "memory_not_saved", "sharing_rank"))
def exp_claims(spark, sf_dir):
    """The published findings that need plans: memory within 6% of the budget; cost falls along it; role sets, roles, planner, shared index in this order at
    every recall target; the gain grows with k; most of the memory of partitions by role is saved; trees gain more than two tiers and than uniform roles.
    For TIER-B no gain is published (partitions by role are as fast as the shared index): there more memory costs time here too."""
    budget = rises = slower = order = 0
    for name in PUBLISHED:
        data = data_of(spark, sf_dir, name)
        plans = pl.plan_spectrum(data, ALPHAS)
        costs = [state_for(data, x).now()[1] for x in plans.values()]
        budget += sum(x.memory > a * 1.06 + 1e-9 for a, x in plans.items())
        if name != "tier_b":
            rises += sum(b > a * 1.02 for a, b in zip(costs, costs[1:], strict=False))
            slower += max(costs) > pl.State(data).now()[1] * 1.02
    data = data_of(spark, sf_dir, "tree_a")
    found = pl.plan_splits(data, 1.4)
    for target in (0.8, 0.9, 0.95, 0.97):
        costs = [by_user("", data, 10.0, target)[8], role_state(data, target=target).now()[1], state_for(data, found, target=target).now()[1], pl.State(data, target=target).now()[1]]
        order += sum(b < a * (1 - 1e-9) for a, b in zip(costs, costs[1:], strict=False))
    by_k = [gains(data, 1.4, k=k)[0] for k in (10.0, 30.0, 60.0, 100.0)]
    role_memory = sum(role_state(data).size) / data.total_docs
    rank = [gains(data_of(spark, sf_dir, n), 1.4)[0] for n in ("tree_0.06", "tier_s", "uni_s")]
    return violations(spark, {
        "budget_exceeded": budget, "cost_rises_with_memory": rises, "slower_than_shared": slower, "order_at_equal_recall": order, "gain_falls_with_k": sum(b < a for a, b in zip(by_k, by_k[1:], strict=False)),
        "memory_not_saved": saving(found.memory, role_memory) >= 0.75, "sharing_rank": sum(b > a for a, b in zip(rank, rank[1:], strict=False)),
    })


_PROFILE = """SELECT '{n}' AS policy, round((SELECT avg(s) FROM picked), 6) AS selectivity, {sel}::DOUBLE AS published_selectivity, round((SELECT count(*) FROM pa) / (SELECT count(*) FROM docs), 6) AS role_overhead, {role}::DOUBLE AS published_role,
  round((SELECT count(*) FROM flat) / (SELECT count(*) FROM docs), 6) AS user_overhead, {user}::DOUBLE AS published_user, (SELECT max(c) FROM (SELECT count(*) AS c FROM set_role GROUP BY rs))::BIGINT AS max_roles"""
_PICKED = ", picked AS (SELECT user_id, coalesce(c, 0) / (SELECT count(*) FROM docs) AS s FROM users LEFT JOIN user_sets USING (user_id) LEFT JOIN (SELECT rs, count(*) AS c FROM flat GROUP BY rs) USING (rs))\n"


@query("exp_policy_profiles", " UNION ALL ".join("SELECT * FROM (" + with_(SAID[n], SETS)[:-1] + _PICKED + _PROFILE.format(n=n, sel=s, role=r, user=u) + ")" for n, (s, r, u) in PUBLISHED.items()))
def exp_policy_profiles(spark, sf_dir):
    """Mean selectivity and memory overheads at 1000 users and 100 roles, beside the published ones."""
    out = None
    for name, (sel, role, user) in PUBLISHED.items():
        r = pol.policy_profile(policy(spark, sf_dir, name))
        one = r.select(F.lit(name).alias("policy"), r6("mean_selectivity").alias("selectivity"), F.lit(sel).alias("published_selectivity"), r6("role_overhead").alias("role_overhead"), F.lit(role).alias("published_role"), r6("user_overhead").alias("user_overhead"), F.lit(user).alias("published_user"), "max_roles")
        out = one if out is None else out.union(one)
    return out


@query("exp_splitree")
def exp_splitree(spark, sf_dir):
    """The disjoint tree against the shared index, by policy: leaves, and model speedup at memory 1."""
    rows = []
    for name in PUBLISHED:
        p = policy(spark, sf_dir, name)
        data, leaves = pl.PlannerInput.collect(p), pt.split_tree(p)
        each = partition_selectivity(p, leaves).filter("permitted > 0").groupBy("rs").agg(F.avg("s").alias("s"), F.sum(F.ln(F.greatest("n_docs", F.lit(2)))).alias("logs"))
        s, logs = pol.role_sets(p).join(each, "rs").agg(F.sum(F.col("s") * F.col("n_users")) / F.sum("n_users"), F.sum(F.col("logs") * F.col("n_users")) / F.sum("n_users")).first()
        rows.append((name, leaves.sizes().count(), round(float(pl.State(data).now()[1] / (logs * (RecallModel().ef_for(0.95, s, 10.0) + B))), 3)))
    return spark.createDataFrame(rows, "policy string, leaves int, model_speedup double")


@query("exp_filtergraph")
def exp_filtergraph(spark, sf_dir):
    """The planner with the cost of the graph that walks permitted nodes, against one such graph over everything."""
    data, model, rows = data_of(spark, sf_dir, "tree_a"), FilterGraphCost(), []

    def cost(s: pl.State) -> float:
        sizes, visits, inside = np.asarray(s.size), np.asarray(s.visits)[:, : s.n_sets], np.asarray(s.inside)[:, : s.n_sets]
        return float((np.where(visits, model.value(sizes[:, None], np.maximum(inside, 1) / sizes[:, None]), 0).sum(axis=0) * s.weight).sum())

    for alpha, found in pl.plan_spectrum(data, [1.2, 1.4, 2.0]).items():
        rows.append((alpha, round(found.memory, 4), round(cost(pl.State(data)) / cost(state_for(data, found)), 3)))
    return spark.createDataFrame(rows, "alpha double, memory double, model_speedup double")


@query("exp_model_parameters")
def exp_model_parameters(spark, sf_dir):
    """Plans under other constants, costed by the default ones: the ranking of moves hardly depends on them."""
    data, rows = data_of(spark, sf_dir, "tree_a"), []
    for name, cost, recall in (("default", GraphCost(), RecallModel()), ("asymptotic", GraphCost.asymptotic(), RecallModel()), ("a_up", GraphCost(1.2, 20), RecallModel()), ("b_down", GraphCost(1.0, 16), RecallModel()), ("beta_up", GraphCost(), RecallModel(4.8, 0.5)), ("gamma_up", GraphCost(), RecallModel(4.0, 0.6))):
        found = pl.plan_splits(data, 1.4, cost, recall)
        rows.append((name, found.n_partitions, round(found.memory, 4), round(pl.State(data).now()[1] / state_for(data, found).now()[1], 3)))
    return spark.createDataFrame(rows, "model string, partitions int, memory double, speedup_by_default_model double")


_STORED = with_(SAID["tree_a"]) + """SELECT round(x / n, 6) AS physical, round((n * 128 + 96 * x) / (n * 224), 6) AS logical FROM (SELECT (SELECT count(*) FROM pa)::DOUBLE AS x, (SELECT count(*) FROM docs)::DOUBLE AS n)"""


@query("exp_physical_logical", _STORED)
def exp_physical_logical(spark, sf_dir):
    """Memory of partitions by role as copies, and as ids with one vector table (128 scalars, 96 links)."""
    p = policy(spark, sf_dir, "tree_a")
    n, x = p.docs.count(), p.pa.count()
    return spark.createDataFrame([(round(x / n, 6), round(logical_overhead(n, x, 128, 32), 6))], "physical double, logical double")


@query("exp_data_size")
def exp_data_size(spark, sf_dir):
    """The same tree over the vectors and over the documents, which are more: plans and curve keep their shape."""
    rows = []
    for table, key in (("embeddings", "vec_id"), ("documents", "doc_id")):
        docs = read(spark, sf_dir, table).select(F.col(key).alias("doc_id"))
        n = docs.count()
        data = pl.PlannerInput.collect(g.gen_tree(spark, docs, n))
        found = pl.plan_splits(data, 1.4)
        rows.append((table, n, found.n_partitions, round(found.memory, 4), round(pl.State(data).now()[1] / state_for(data, found).now()[1], 3)))
    return spark.createDataFrame(rows, "table string, n_docs long, partitions int, memory double, model_speedup double")


_RATIO = "SELECT policy, round(max(memory) FILTER (strategy = 'user_part') / max(memory) FILTER (strategy = 'role_part'), 2) AS memory_ratio, round(max(cost) FILTER (strategy = 'role_part') / max(cost) FILTER (strategy = 'user_part'), 3) AS cost_ratio FROM ("
_USER_ROLE = [(n, 10.0, 0.95) for n in ("tier_a", "tier_b", "uni_a")]


@query("exp_user_vs_role", _RATIO + extremes_sql(_USER_ROLE) + ") GROUP BY policy")
def exp_user_vs_role(spark, sf_dir):
    """Memory of partitions by user over that by role, and the cost ratio that it buys."""
    rows = []
    for name, k, target in _USER_ROLE:
        data = data_of(spark, sf_dir, name)
        user, role = by_user(name, data, k, target), told(name, "role_part", role_state(data))
        rows.append((name, round(user[4] / role[4], 2), round(role[8] / user[8], 3)))
    return spark.createDataFrame(rows, "policy string, memory_ratio double, cost_ratio double")


@query("exp_role_splitting", with_(SAID["tree_a"]) + "SELECT ways, round(avg(ways * ln(greatest(c / ways, 2))), 4) AS mean_log_cost FROM (SELECT role_id, count(*) AS c FROM pa GROUP BY role_id), (VALUES (1::BIGINT), (2), (4)) t(ways) GROUP BY ways")
def exp_role_splitting(spark, sf_dir):
    """Cost of a role in one partition against the same role cut into 2 and 4, at one depth."""
    sizes = policy(spark, sf_dir, "tree_a").pa.groupBy("role_id").agg(F.count("*").alias("c"))
    ways = spark.createDataFrame([(1,), (2,), (4,)], "ways long")
    cost = F.col("ways") * F.ln(F.greatest(F.col("c") / F.col("ways"), F.lit(2.0)))
    return sizes.join(F.broadcast(ways)).groupBy("ways").agg(F.round(F.avg(cost), 4).alias("mean_log_cost"))


@query("exp_fit_models")
def exp_fit_models(spark, sf_dir):
    """Beta and gamma fitted to recall of exact search with a filter afterwards, over depths, on the vectors and the published workload."""
    from aclvec.operators import measures as me
    from aclvec.operators import search as se
    from aclvec.plans.catalog_parts import parts
    from aclvec.plans.catalog_policy import on_vectors, workload
    from aclvec.plans.policies_sql import SMALL_UNI
    from aclvec.sources.tables import vectors

    p = on_vectors(g.gen_uniform, **SMALL_UNI, m_r=1, m_p_factor=4)(spark, sf_dir)
    q = workload(spark, sf_dir).withColumn("user_id", F.col("query_id") % 150)
    v, part = vectors(spark, sf_dir), parts(p, "rls")
    truth = se.ground_truth(q, v, p).cache()
    s = float(me.system_selectivity(p, part).first()[0])
    efs = [10, 20, 40, 60, 80, 100, 150, 200, 300, 400]
    got = {r.ef: r.recall for r in se.recall_by_depth(q, v, p, part, truth, efs).collect()}
    model, rmse = fit_recall(efs, [s] * len(efs), [10] * len(efs), [got[e] for e in efs])
    return spark.createDataFrame([(round(s, 4), round(model.beta, 4), round(model.gamma, 4), round(rmse, 4))], "selectivity double, beta double, gamma double, rmse double")


@query("exp_updates")
def exp_updates(spark, sf_dir):
    """Through the update operators: after 1, 3 and 6 role insertions and deletions at alpha 1.5, model cost over that of a fresh plan, partitions to rebuild, and differences from partitions filled anew."""
    p = policy(spark, sf_dir, "tree_a")
    start = up.PolicyState.scratch(p, pl.plan_splits(pl.PlannerInput.collect(p), 1.5).part_role(spark))
    ua, pa = g.gen_role_insertions(p, 6)
    gone = [r.role_id for r in g.gen_role_deletions(p, 6).collect()]
    rows = []
    for kind in ("insert", "delete"):
        s = start
        for i in range(6):
            s = up.add_role(s, 900 + i, pa.filter(F.col("role_id") == 900 + i), ua.filter(F.col("role_id") == 900 + i)) if kind == "insert" else up.drop_role(s, gone[i])
            if i + 1 in (1, 3, 6):
                data = pl.PlannerInput.collect(s.policy)
                fresh = state_for(data, pl.plan_splits(data, 1.5)).now()[1]
                rows.append((kind, i + 1, round(up.model_cost(s) / fresh, 4), up.dirty_partitions(start, s).count(), up.state_violations(s).first()[0]))
    return spark.createDataFrame(rows, "kind string, n_ops int, cost_ratio double, dirty_partitions long, differences long")


@query("exp_planner_scale")
def exp_planner_scale(spark, sf_dir):
    """Moves and classes as roles grow."""
    docs, rows = read(spark, sf_dir, "documents").select("doc_id"), []
    n = docs.count()
    for n_roles in (25, 50, 100):
        data = pl.PlannerInput.collect(g.gen_tree(spark, docs, n, n_roles=n_roles))
        found = pl.plan_splits(data, 1.4)
        rows.append((n_roles, len(data.n_docs), len(found.trace), found.n_partitions))
    return spark.createDataFrame(rows, "n_roles int, classes int, moves int, partitions int")


@query("exp_cover_saves", zeros("more_visits", "uncovered"))
def exp_cover_saves(spark, sf_dir):
    """The greedy cover in the online path: whether users visit more partitions than homes in sum, and documents it misses."""
    p = policy(spark, sf_dir, "tier_a")
    part_role = pl.plan_splits(pl.PlannerInput.collect(p), 1.9).part_role(spark)
    home, cover = ro.online(p, part_role, "home"), ro.online(p, part_role)
    visits = lambda x: x.route.join(pol.role_sets(p), "rs").agg(F.sum("n_users")).first()[0]
    return violations(spark, {"more_visits": visits(cover) <= visits(home), "uncovered": ro.cover_violations(p, cover).first()[0]})
