"""The split planner: whole roles leave the largest partition, best gain per unit of storage first.

Documents are compressed to access classes by Spark. A class lies in a partition
if one of the partition's roles sees it, so storage and selectivity after a move
are sums over classes, and no union of document sets is ever built. Up to
`MAX_ENTRIES` cells of classes x roles the driver holds the classes and sums them
itself, in pieces; beyond, they stay in Spark, tasks sum the same pieces, and only
sums reach the driver. Both ways give the same plan. What the driver always holds
is role sets x roles, whose size is checked.
"""

from __future__ import annotations

from copy import copy
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.functions.models import GraphCost, RecallModel
from aclvec.operators.policy import Policy, access_classes, role_sets

#: Cells (class, role) that the driver takes, cells (role set, role) at most, and classes of a piece.
MAX_ENTRIES, MAX_SETS, PIECE = 16_000_000, 64_000_000, 4_096


def move_sums(sees, permitted, n_docs, src, dst, roles):
    """Sizes (2, role) and permitted documents (2, question, role) of two partitions, given as role masks, after each role moved."""
    cols = sees[:, roles]
    held = [(counts > 0).astype(np.float32) for counts in ((sees @ src)[:, None] - cols, (sees @ dst)[:, None] + cols)]
    return np.stack([n_docs @ h for h in held]), np.stack([permitted.T @ h for h in held])


def part_sums(sees, permitted, n_docs, masks):
    """Sizes (partition) and permitted documents (question, partition) of partitions, given as role masks in columns."""
    held = (sees @ masks > 0).astype(np.float32)
    return n_docs @ held, permitted.T @ held


def leaf_sums(sees, permitted, n_docs, cuts, leaf):
    """Of the classes in a leaf of a tree: documents, classes, documents by role, and how many classes a question may see with and without each role."""
    at = np.zeros(len(sees), int)
    for node, role, new in cuts:
        at[(at == node) & (sees[:, role] == 0)] = new
    mine = at == leaf
    x, may = sees[mine], (permitted[mine] > 0).astype(np.float32)
    return np.array([n_docs[mine].sum()]), np.array([float(mine.sum())]), n_docs[mine] @ x, may.T @ x, may.T @ (1 - x)


@dataclass
class PlannerInput:
    """Class and role-set matrices. roles: ids of the columns; sees: class x role; sets: role set x role.

    Beyond the bound `classes` (role_set, n_docs) stands for sees and n_docs, which are None.
    """

    roles: np.ndarray
    sees: np.ndarray | None
    n_docs: np.ndarray | None
    sets: np.ndarray
    weight: np.ndarray
    total_docs: float
    classes: DataFrame | None = None
    seen_docs: float | None = None

    @property
    def orphans(self) -> float:
        """Documents that no role sees."""
        return self.total_docs - float(self.n_docs.sum() if self.seen_docs is None else self.seen_docs)

    @classmethod
    def collect(cls, p: Policy, weights: DataFrame | None = None, max_entries: int | None = None) -> PlannerInput:
        """From a policy. `weights`: rs, weight to use in place of the number of users."""
        n, classes, sets = p.docs.count(), access_classes(p).select("role_set", "n_docs"), role_sets(p)
        if weights is not None:
            sets = sets.join(weights, "rs", "left").withColumn("n_users", F.coalesce("weight", F.lit(0.0)))
        roles = np.array(sorted(r.role_id for r in p.roles.collect()))  # one row a role
        if (cells := sets.count() * len(roles)) > MAX_SETS:
            raise ValueError(f"{cells} cells of role sets and roles; the bound is {MAX_SETS}")
        users = sorted((list(r.role_set), float(r.n_users)) for r in sets.select("role_set", "n_users").collect())
        own = matrix(roles, [x for x, _ in users])
        weight, (n_classes, seen) = np.array([w for _, w in users]), classes.agg(F.count("*"), F.sum("n_docs")).first()
        if n_classes * len(roles) > (MAX_ENTRIES if max_entries is None else max_entries):
            return cls(roles, None, None, own, weight, float(n), classes.checkpoint() if p.docs.sparkSession.sparkContext.getCheckpointDir() else classes.persist(), float(seen))
        found = sorted((list(r.role_set), r.n_docs) for r in classes.collect())
        return cls(roles, matrix(roles, [x for x, _ in found]), np.array([c for _, c in found], float), own, weight, float(n))

    def summed(self, asks: np.ndarray, work, *args) -> list[np.ndarray]:
        """The sums over all classes of what `work` returns for a piece of them; asks: the questions' roles."""
        if self.classes is None:
            total = None
            for i in range(0, max(1, len(self.n_docs)), PIECE):
                got = piece_sums(self.sees[i : i + PIECE], self.n_docs[i : i + PIECE], asks, work, args)
                total = got if total is None else [x + y for x, y in zip(total, got, strict=True)]
            return total
        roles, shapes = self.roles, [x.shape for x in piece_sums(np.zeros((0, len(self.roles)), np.float32), np.zeros(0), asks, work, args)]
        sent = self.classes.sparkSession.sparkContext.broadcast((asks, args))

        def run(batches):
            asks, args = sent.value
            total = None
            for b in batches:
                for i in range(0, b.num_rows, PIECE):
                    part = b.slice(i, PIECE)
                    n_docs = part.column(1).to_numpy(zero_copy_only=False).astype(float)
                    got = piece_sums(matrix(roles, part.column(0).to_pylist()), n_docs, asks, work, args)
                    total = got if total is None else [x + y for x, y in zip(total, got, strict=True)]
            if total is not None:
                flat = np.concatenate([x.ravel() for x in total])
                cells = np.flatnonzero(flat)
                yield pa.RecordBatch.from_arrays([pa.array(cells, pa.int64()), pa.array(flat[cells], pa.float64())], names=["cell", "value"])

        rows = self.classes.mapInArrow(run, "cell long, value double").groupBy("cell").agg(F.sum("value").alias("value")).toPandas()
        flat = np.zeros(sum(int(np.prod(x)) for x in shapes))
        flat[rows["cell"].to_numpy(np.int64)] = rows["value"].to_numpy()
        ends = np.cumsum([int(np.prod(x)) for x in shapes])
        return [flat[e - int(np.prod(x)) : e].reshape(x) for x, e in zip(shapes, ends, strict=True)]


def matrix(roles: np.ndarray, sets: list[list[int]]) -> np.ndarray:
    """A row of zeros and ones for each set of role ids."""
    out = np.zeros((len(sets), len(roles)), np.float32)
    sizes = list(map(len, sets))
    out[np.repeat(np.arange(len(sets)), sizes), np.searchsorted(roles, [x for one in sets for x in one])] = 1
    return out


def piece_sums(sees, n_docs, asks, work, args) -> list[np.ndarray]:
    permitted = (sees @ asks.T > 0) * n_docs[:, None].astype(np.float32)
    return [np.asarray(x, float) for x in work(sees, permitted.astype(np.float32), n_docs, *args)]


@dataclass
class Plan:
    """home: the partition of each role; sizes by partition; the moves that led there."""

    roles: list[int]
    home: list[int]
    sizes: list[float]
    total_docs: float
    trace: list[dict] = field(default_factory=list)

    @property
    def memory(self) -> float:
        return sum(self.sizes) / self.total_docs if self.total_docs else 0.0

    @property
    def n_partitions(self) -> int:
        return len(self.sizes)

    def part_role(self, spark: SparkSession) -> DataFrame:
        """partition_id, role_id: one row a role."""
        return spark.createDataFrame([(int(h), int(r)) for r, h in zip(self.roles, self.home, strict=True)], "partition_id int, role_id int")

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        cols = "step int, src int, dst int, role_id int, d_storage double, gain_r double, gain_u double, memory double, sbar double, ef double"
        names = [c.split()[0] for c in cols.split(", ")]
        return spark.createDataFrame([tuple(t[c] for c in names) for t in self.trace], cols)


class State:
    """A partitioning of roles and its model costs. `orphans`: whether the first partition keeps documents that no role sees."""

    def __init__(self, data: PlannerInput, cost=GraphCost(), recall=RecallModel(), target: float = 0.95, k: float = 10.0, per_partition_ef: bool = False, orphans: str = "drop"):
        self.data, self.cost, self.model, self.target, self.k = data, cost, recall, target, k
        self.per_partition_ef, self.orphans = per_partition_ef, data.orphans if orphans == "keep" else 0.0
        n_roles = len(data.roles)
        self.home = np.zeros(n_roles, int)
        # Questions: users' role sets, then each role alone.
        asks = np.concatenate((data.sets, np.eye(n_roles, dtype=np.float32)))
        self.asks, self.n_sets = asks > 0, len(data.sets)
        self.weight = data.weight / max(data.weight.sum(), 1e-12)
        self.size = [data.total_docs]  # one partition also holds documents without a role
        self.visits = [self.asks.any(axis=1)]
        self.inside = [data.summed(asks, part_sums, np.ones((n_roles, 1), np.float32))[1][:, 0]]

    def sums(self, work, *args) -> list[np.ndarray]:
        return self.data.summed(self.asks.astype(np.float32), work, *args)

    def members(self, part: int) -> np.ndarray:
        return np.flatnonzero(self.home == part)

    def summary(self, sizes, visits, inside) -> tuple[float, float, float, float]:
        """Mean cost of roles and of users, mean selectivity, depth. Arrays: partition first, then question, then candidates."""
        sizes, visits, inside = np.asarray(sizes, float), np.asarray(visits, bool), np.asarray(inside, float)
        ratio = np.where(visits, inside / np.maximum(sizes, 1)[:, None], 0)
        n = visits.sum(axis=0)
        s = ratio.sum(axis=0) / np.maximum(n, 1)
        sbar = float((s[: self.n_sets] * self.weight).sum())
        ef = float(self.model.ef_for(self.target, max(sbar, 1e-12), self.k))
        if self.per_partition_ef:
            each = np.where(visits, self.cost.value(sizes[:, None], self.model.ef_for(self.target, np.maximum(ratio, 1e-12), self.k)), 0)
        else:
            each = visits * self.cost.value(sizes, ef)[:, None]
        total = each.sum(axis=0)
        return float(total[self.n_sets :].mean()), float((total[: self.n_sets] * self.weight).sum()), sbar, ef

    def now(self) -> tuple[float, float, float, float]:
        return self.summary(self.size, self.visits, self.inside)

    def after(self, src: int, dst: int, roles: np.ndarray):
        """Sizes, visits and permitted documents of src and dst, each after one of the roles moved; arrays end with the role."""
        here, there = self.home == src, self.home == dst
        sizes, inside = self.sums(move_sums, here.astype(np.float32), there.astype(np.float32), roles)
        mine = self.asks[:, roles].astype(int)
        visits = self.asks[:, here].sum(axis=1)[:, None] - mine > 0, self.asks[:, there].sum(axis=1)[:, None] + mine > 0
        return [(z + self.orphans * (part == 0), v, x) for z, v, x, part in zip(sizes, visits, inside, (src, dst), strict=True)]

    def candidates(self, src: int, dst: int) -> list[dict]:
        """Every role of src with its storage delta and gains, if it moved to dst: all of them in a few matrix products."""
        c_r, c_u, _, _ = self.now()
        roles, data = self.members(src), self.data
        old = self.size[src] + (self.size[dst] if dst < len(self.size) else 0)
        # (question, candidate) for both partitions after the move.
        after = [(size, visit, np.where(visit, inside / np.maximum(size, 1)[None], 0)) for size, visit, inside in self.after(src, dst, roles)]
        rest = [p for p in range(len(self.size)) if p not in (src, dst)]
        sizes = np.array([self.size[p] for p in rest])
        visits = np.array([self.visits[p] for p in rest]).reshape(len(rest), len(self.asks))
        ratios = np.where(visits, np.array([self.inside[p] for p in rest]).reshape(visits.shape) / np.maximum(sizes, 1)[:, None], 0)
        n = visits.sum(axis=0)[:, None] + after[0][1] + after[1][1]
        s = (ratios.sum(axis=0)[:, None] + after[0][2] + after[1][2]) / np.maximum(n, 1)
        sbar = self.weight @ s[: self.n_sets]
        ef = np.array([float(self.model.ef_for(self.target, max(x, 1e-12), self.k)) for x in sbar])
        if self.per_partition_ef:
            deep = lambda size, ratio: self.cost.value(size, self.model.ef_for(self.target, np.maximum(ratio, 1e-12), self.k))
            total = np.where(visits, deep(sizes[:, None], ratios), 0).sum(axis=0)[:, None]
            total = total + sum(np.where(v, deep(z[None], r), 0) for z, v, r in after)
        else:
            total = visits.T.astype(float) @ self.cost.value(sizes[:, None], ef[None]) if rest else 0.0
            total = total + sum(v * self.cost.value(z, ef)[None] for z, v, _ in after)
        new_r, new_u = total[self.n_sets :].mean(axis=0), self.weight @ total[: self.n_sets]
        return [
            {"r": r, "role_id": int(data.roles[r]), "d_storage": float(after[0][0][i] + after[1][0][i] - old), "gain_r": float(c_r - new_r[i]), "gain_u": float(c_u - new_u[i]), "sbar": float(sbar[i]), "ef": float(ef[i])}
            for i, r in enumerate(roles.tolist())
        ]

    def move(self, src: int, dst: int, r: int) -> None:
        moved = self.after(src, dst, np.array([r]))
        if dst == len(self.size):
            for x in (self.size, self.visits, self.inside):
                x.append(None)
        self.home[r] = dst
        for part, (size, visit, inside) in zip((src, dst), moved, strict=True):
            self.size[part], self.visits[part], self.inside[part] = float(size[0]), visit[:, 0], inside[:, 0]

    def routed(self, route: DataFrame, names: list[str] | None = None) -> State:
        """The same partitions searched along `route` (rs, part), as a cover, in place of all homes. `names`: of the partitions, else their numbers."""
        names = names or [str(i) for i in range(len(self.size))]
        keys = {",".join(str(x) for x in self.data.roles[s > 0].tolist()): i for i, s in enumerate(self.data.sets)}
        out = copy(self)
        out.visits = [v.copy() for v in self.visits]
        for v in out.visits:
            v[: self.n_sets] = False
        for r in route.select("rs", "part").collect():  # role sets x partitions
            out.visits[names.index(r.part)][keys[r.rs]] = True
        return out

    def plan(self, trace: list[dict]) -> Plan:
        return Plan(self.data.roles.tolist(), self.home.tolist(), [float(s) for s in self.size], self.data.total_docs, list(trace))


def gain_of(c: dict, objective: str) -> float:
    """What a move is worth: to users, to single roles, or to both."""
    return {"both": c["gain_r"] + c["gain_u"], "user": c["gain_u"], "role": c["gain_r"]}[objective]


def rank_key(c: dict, score_mode: str = "gain", eps: float = 1e-6, objective: str = "both") -> tuple:
    """Moves that need no storage come first, then gain per storage; ties go to the smaller role."""
    gain = gain_of(c, objective)
    if score_mode == "eps_ratio":
        return (0, gain / (max(c["d_storage"], 0.0) + eps), -c["role_id"])
    return (1, gain, -c["role_id"]) if c["d_storage"] <= 0 else (0, gain / c["d_storage"], -c["role_id"])


def largest_splittable(state: State, skip: set[int] = frozenset()) -> int | None:
    """The largest partition of several roles; ties go to the smaller id."""
    many = [p for p in range(len(state.size)) if p not in skip and (state.home == p).sum() > 1]
    return max(many, key=lambda p: (state.size[p], -p), default=None)


def plan_splits(data: PlannerInput, alpha: float = 1.4, cost=GraphCost(), recall=RecallModel(), target: float = 0.95, k: float = 10.0, eta: float = 0.02, budget_mode: str = "overshoot", tol: float = 0.06, score_mode: str = "gain", per_partition_ef: bool = False, max_moves: int | None = None, objective: str = "both", orphans: str = "drop") -> Plan:
    """The greedy search. `objective`: whose mean cost ranks the moves ('user', 'role' or 'both'). `orphans`: 'keep' leaves documents without a role in the first partition. `budget_mode`: 'overshoot' checks the budget before a move and undoes a last one beyond alpha * (1 + tol); 'strict' takes only moves within it."""
    state = State(data, cost, recall, target, k, per_partition_ef=per_partition_ef, orphans=orphans)
    budget, trace, exhausted = alpha * data.total_docs, [], set()
    full = lambda: sum(state.size) > budget + 1e-9
    while not full() and (max_moves is None or len(trace) < max_moves):
        src = largest_splittable(state, exhausted)
        if src is None:
            break
        dst, moved = len(state.size), False
        while not full() and (max_moves is None or len(trace) < max_moves):
            if (state.home == src).sum() < 2:
                break
            c_u = state.now()[1]
            useful = lambda c: c["gain_r"] > 1e-12 if objective == "both" else gain_of(c, objective) > 1e-12
            good = [c for c in state.candidates(src, dst) if useful(c) and (objective == "role" or -c["gain_u"] < eta * c_u)]
            if budget_mode == "strict":
                good = [c for c in good if sum(state.size) + c["d_storage"] <= budget + 1e-9]
            if not good:
                break
            best = max(good, key=lambda c: rank_key(c, score_mode, objective=objective))
            if sum(state.size) + best["d_storage"] > budget * (1 + tol) + 1e-9:
                return state.plan(trace)  # the last move would overshoot too far
            state.move(src, dst, best["r"])
            moved = True
            exhausted -= {src, dst}
            trace.append({"step": len(trace) + 1, "src": src, "dst": dst, "role_id": best["role_id"], "d_storage": best["d_storage"], "gain_r": best["gain_r"], "gain_u": best["gain_u"], "memory": sum(state.size) / data.total_docs, "sbar": best["sbar"], "ef": best["ef"]})
            if largest_splittable(state) != src:
                break
        if not moved:
            exhausted.add(src)
    return state.plan(trace)


def state_of(data: PlannerInput, homes: dict[int, int], **how) -> State:
    """The state of a given partitioning: role id -> partition."""
    state = State(data, **how)
    ids = sorted(set(homes.values()))
    at = {p: i for i, p in enumerate(ids)}
    state.home = np.array([at[homes[r]] for r in data.roles.tolist()])
    masks = np.stack([state.home == i for i in range(len(ids))], axis=1)
    sizes, inside = state.sums(part_sums, masks.astype(np.float32))
    state.size = [float(x) + state.orphans * (i == 0) for i, x in enumerate(sizes)]
    state.visits = [(state.asks & m).any(axis=1) for m in masks.T]
    state.inside = list(inside.T)
    return state


def plan_spectrum(data: PlannerInput, alphas: list[float], tol: float = 0.06, **how) -> dict[float, Plan]:
    """Plans for several budgets from one run: in overshoot mode a smaller budget only ends the path sooner."""
    whole = plan_splits(data, alpha=float("inf"), tol=tol, **how)
    out = {}
    for alpha in alphas:
        n, memory = 0, 1.0
        for t in whole.trace:
            if memory > alpha + 1e-12 or t["memory"] > alpha * (1 + tol) + 1e-12:
                break
            n, memory = n + 1, t["memory"]
        homes = {int(r): 0 for r in data.roles} | {t["role_id"]: t["dst"] for t in whole.trace[:n]}
        own = {x: how[x] for x in ("cost", "recall", "target", "k", "per_partition_ef", "orphans") if x in how}
        out[alpha] = (state_of(data, homes, **own) if n else State(data, **own)).plan(whole.trace[:n])
    return out


def set_partitions(n: int):
    """All ways to put n things into groups, as group numbers."""

    def grow(prefix: list[int], most: int):
        if len(prefix) == n:
            yield prefix
            return
        for g in range(most + 2):
            yield from grow([*prefix, g], max(most, g))

    yield from grow([], -1)


def plan_exact(data: PlannerInput, alpha: float, max_roles: int = 8, **how) -> tuple[float, dict[int, int]]:
    """The least mean user cost within the budget over all partitionings of few roles: the yardstick of the greedy search."""
    if len(data.roles) > max_roles:
        raise ValueError(f"{len(data.roles)} roles; at most {max_roles}")
    best = (float("inf"), {})
    for groups in set_partitions(len(data.roles)):
        homes = dict(zip(data.roles.tolist(), groups, strict=True))
        state = state_of(data, homes, **how)
        if len(set(groups)) == 1:
            state.size = [data.total_docs]
        if sum(state.size) <= alpha * data.total_docs + 1e-9 and (c := state.now()[1]) < best[0] - 1e-12:
            best = (c, homes)
    return best


def storage_delta(p: Policy, part_role: DataFrame, src: int, dst: int) -> DataFrame:
    """role_id, d_storage for all roles of src at once: its documents, less those already in dst, less those that only it holds in src."""
    homes = part_role.select("role_id", "partition_id")
    rows = p.pa.join(F.broadcast(homes), "role_id")  # one row a role
    per_doc = rows.groupBy("doc_id").agg(F.collect_list(F.when(F.col("partition_id") == src, F.col("role_id"))).alias("in_src"), F.max((F.col("partition_id") == dst).cast("int")).alias("in_dst"))
    each = per_doc.select(F.explode("in_src").alias("role_id"), F.size("in_src").alias("n_src"), "in_dst")
    return each.groupBy("role_id").agg((F.count("*") - F.sum("in_dst") - F.sum((F.col("n_src") == 1).cast("int"))).alias("d_storage"))


def candidate_moves(p: Policy, part_role: DataFrame, src: int, dst: int, **how) -> list[dict]:
    """Candidates of any given state, with their score."""
    data = PlannerInput.collect(p)
    homes = {r.role_id: r.partition_id for r in part_role.collect()}
    state = State(data, **how) if set(homes.values()) == {src} else state_of(data, homes, **how)
    out = state.candidates(src, dst)
    for c in out:
        c["score"] = (c["gain_r"] + c["gain_u"]) / c["d_storage"] if c["d_storage"] > 0 else c["gain_r"] + c["gain_u"]
    return out
