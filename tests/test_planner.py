"""The hand policy's golden values, the storage identity against unions, and the shape of plans."""

import itertools

import numpy as np
import pandas as pd
import pytest

from aclvec.functions.models import GraphCost, RecallModel
from aclvec.operators import generators as g
from aclvec.operators import planner as pl
from aclvec.operators import routing as ro
from aclvec.operators.partitioning import role_homes, split_tree
from aclvec.operators.policy import auth_role_sets
from aclvec.plans.catalog_policy import POLICY

HOW = {"cost": GraphCost(1.0, 0.0), "recall": RecallModel(4.0, 0.5), "target": 0.95, "k": 2.0}


@pytest.fixture(scope="module")
def h1(spark):
    return pl.PlannerInput.collect(g.hand_h1(spark))


def test_one_partition(h1):
    c_r, c_u, sbar, ef = pl.State(h1, **HOW).now()
    assert (round(sbar, 6), round(ef, 5), round(c_u, 5), round(c_r, 5)) == (0.402778, 6.13792, 15.25217, 15.25217)
    c_r, c_u, sbar, ef = pl.state_of(h1, dict.fromkeys((1, 2, 3, 4), 0), **HOW).now()
    assert (round(sbar, 6), round(ef, 5), round(c_u, 5)) == (0.439394, 5.62643, 13.49159)


@pytest.mark.parametrize(
    ("orphan", "want"),
    [
        (False, {1: (2, 6.156457, 4.958635, 5.557546), 2: (3, 4.703858, 4.380248, 3.028035), 3: (3, 5.340837, 3.475323, 2.938720), 4: (2, 5.779839, 4.687825, 5.233832)}),
        (True, {1: (1, 7.917035, 6.719213, 14.636247), 2: (2, 6.464435, 6.140825, 6.302630), 3: (2, 7.101415, 5.235900, 6.168658), 4: (1, 7.540416, 6.448403, 13.988819)}),
    ],
)
def test_candidates(h1, orphan, want):
    state = pl.State(h1, **HOW) if orphan else pl.state_of(h1, dict.fromkeys((1, 2, 3, 4), 0), **HOW)
    for c in state.candidates(0, 1):
        d, r, u, score = want[c["role_id"]]
        assert c["d_storage"] == d
        assert (c["gain_r"], c["gain_u"], (c["gain_r"] + c["gain_u"]) / d) == pytest.approx((r, u, score), abs=2e-5)


@pytest.mark.parametrize(
    ("homes", "want"),
    [
        ({1: 1, 2: 0, 3: 0, 4: 0}, (0.642857, 3.845675, 8.532956, 7.335134)),
        ({1: 0, 2: 0, 3: 1, 4: 1}, (0.760417, 3.251138, 6.384965, 5.633793)),
        ({1: 0, 2: 1, 3: 2, 4: 2}, (0.895833, 2.759687, 4.836347, 4.105478)),
        ({1: 0, 2: 1, 3: 2, 4: 3}, (1.0, 2.472219, 4.311087, 3.322217)),
    ],
)
def test_plans(h1, homes, want):
    c_r, c_u, sbar, ef = pl.state_of(h1, homes, **HOW).now()
    assert (sbar, ef, c_u, c_r) == pytest.approx(want, abs=2e-5)


def test_first_move_and_undo(h1):
    found = pl.plan_splits(h1, 1.2, **HOW)
    assert found.trace[0]["role_id"] == 1
    for alpha in (1.0, 1.1, 1.3, 2.0):
        assert pl.plan_splits(h1, alpha, **HOW).memory <= alpha * 1.06 + 1e-9
        assert pl.plan_splits(h1, alpha, budget_mode="strict", **HOW).memory <= alpha + 1e-9


def random_input(rng, n_roles=7, n_classes=30) -> pl.PlannerInput:
    sees = (rng.random((n_classes, n_roles)) < 0.3).astype(np.float32)
    sees = sees[sees.any(axis=1)]
    n = rng.integers(1, 20, len(sees)).astype(float)
    sets = (rng.random((9, n_roles)) < 0.3).astype(np.float32)
    sets = sets[sets.any(axis=1)]
    return pl.PlannerInput(np.arange(n_roles), sees, n, sets, np.ones(len(sets)), float(n.sum()) + 5)


def test_candidates_equal_states_built_anew():
    rng = np.random.default_rng(3)
    for _ in range(20):
        data = random_input(rng)
        homes = {r: int(rng.integers(0, 3)) for r in range(7)}
        homes |= {0: 0, 1: 0, 2: 1, 3: 2}
        for per_partition in (False, True):
            state = pl.state_of(data, homes, per_partition_ef=per_partition)
            c_r, c_u, _, _ = state.now()
            for c in state.candidates(0, 1):
                moved = pl.state_of(data, {**homes, c["r"]: 1}, per_partition_ef=per_partition)
                if len(set({**homes, c["r"]: 1}.values())) == 3:
                    n_r, n_u, sbar, ef = moved.now()
                    assert c["d_storage"] == pytest.approx(sum(moved.size) - sum(state.size))
                    assert (c["gain_r"], c["gain_u"], c["ef"]) == pytest.approx((c_r - n_r, c_u - n_u, ef), rel=1e-4, abs=1e-4)


def test_unbounded_budget_ends_at_whole_roles(spark):
    docs = spark.range(2000).withColumnRenamed("id", "doc_id")
    data = pl.PlannerInput.collect(g.gen_tree(spark, docs, 2000, n_roles=25))
    found = pl.plan_splits(data, float("inf"))
    assert found.n_partitions == 25
    assert sum(found.sizes) == pytest.approx(float((data.n_docs @ data.sees).sum()))
    assert found.home == pl.plan_splits(data, float("inf")).home


def test_tree_beats_the_shared_index_as_published(spark):
    docs = spark.range(20_000).withColumnRenamed("id", "doc_id")
    data = pl.PlannerInput.collect(g.gen_tree(spark, docs, 20_000))
    speed = {}
    for k in (10.0, 100.0):
        found = pl.plan_splits(data, 1.4, k=k)
        cost = pl.state_of(data, dict(zip(found.roles, found.home, strict=True)), k=k).now()[1]
        speed[k] = pl.State(data, k=k).now()[1] / cost
    assert speed[10.0] >= 6 and speed[100.0] > speed[10.0]


def test_cover_of_a_plan(spark):
    p = g.hand_h1(spark)
    part = role_homes(p, pl.plan_splits(pl.PlannerInput.collect(p), 1.2, **HOW).part_role(spark))
    for method in ("greedy_count", "greedy_ratio", "exact", "home"):
        assert ro.cover_violations(p, ro.routed(part, ro.cover(p, part, method))).first()[0] == 0


def test_bound_is_checked(spark):
    p = g.hand_h1(spark)
    with pytest.raises(ValueError):
        pl.plan_exact(pl.PlannerInput.collect(p), 1.0, max_roles=3)


def test_classes_that_stay_in_spark_give_the_same_plans(spark, sf):
    """Forced beyond the driver's bound, sums come from tasks: plans, costs and trees are those of classes on the driver."""
    p = POLICY["uni_a"](spark, sf)
    near, far = pl.PlannerInput.collect(p), pl.PlannerInput.collect(p, max_entries=0)
    assert far.sees is None and far.orphans == near.orphans
    a, b = (pl.plan_splits(x, 1.3, max_moves=3) for x in (near, far))
    assert a.home == b.home and a.sizes == b.sizes and len(a.trace) == 3
    homes = dict(zip(a.roles, a.home, strict=True))
    assert pl.state_of(near, homes).now() == pytest.approx(pl.state_of(far, homes).now())
    whole, apart = split_tree(p), split_tree(p, max_entries=0)
    for tree in (whole, apart):
        placed = [r.doc_id for r in tree.part_doc.collect()]
        assert len(placed) == len(set(placed)) and set(placed) == {r.doc_id for r in p.pa.select("doc_id").distinct().collect()}
        assert ro.cover_violations(p, tree).first()[0] == 0
        assert {tuple(r) for r in tree.route.collect()} == {tuple(r) for r in auth_role_sets(p).join(tree.part_doc, "doc_id").select("rs", "part").distinct().collect()}
    assert {tuple(r) for r in whole.part_doc.collect()} == {tuple(r) for r in apart.part_doc.collect()}


def test_pieces_change_nothing(monkeypatch):
    data = random_input(np.random.default_rng(8), 7, 60)
    homes = {r: r % 3 for r in range(7)}
    one, plan = pl.state_of(data, homes), pl.plan_splits(data, 1.6)
    monkeypatch.setattr(pl, "PIECE", 7)
    assert pl.state_of(data, homes).now() == pytest.approx(one.now()) and pl.plan_splits(data, 1.6).home == plan.home


def test_objectives_and_orphans(h1):
    for objective, best in (("user", 1), ("role", 0)):
        found = pl.plan_splits(h1, 1.4, objective=objective, **HOW)
        worth = [t["gain_u" if best else "gain_r"] for t in found.trace]
        assert worth and min(worth) > 0
    kept = pl.plan_splits(h1, 1.6, orphans="keep", **HOW)
    assert h1.orphans == 1 and kept.sizes[0] == 1 + float(h1.n_docs[(h1.sees[:, np.array(kept.home) == 0] > 0).any(axis=1)].sum())


def test_cover_costs_no_more_than_homes(spark, sf):
    p = POLICY["n1"](spark, sf)
    data = pl.PlannerInput.collect(p)
    plan = pl.plan_splits(data, 1.4)
    state = pl.state_of(data, dict(zip(plan.roles, plan.home, strict=True)))
    part = ro.online(p, plan.part_role(spark))
    assert ro.cover_violations(p, part).first()[0] == 0
    covered = state.routed(part.route)
    assert np.array(covered.visits).sum() <= np.array(state.visits).sum()
    homes = state.routed(ro.online(p, plan.part_role(spark), "home").route)
    assert homes.now() == pytest.approx(state.now())


def test_exact_cover_of_many_partitions():
    """Fourteen partitions: the greedy cover takes the large one first, the exact cover doesn't need it."""
    rows = [(f"p{i:02}", f"c{i}", 1, 2) for i in range(13)] + [("q", f"c{i}", 1, 1 << 20) for i in range(12)]
    rows = pd.DataFrame(rows, columns=["part", "cls", "n_docs", "size"])
    assert "q" in ro._greedy(rows, False) and ro._exact(rows) == [f"p{i:02}" for i in range(13)]
    rng = np.random.default_rng(4)
    for _ in range(20):
        held = {f"p{i}": (int(rng.integers(2, 50)), set(rng.choice(8, rng.integers(1, 5), False).tolist())) for i in range(7)}
        rows = pd.DataFrame([(k, str(c), 1, size) for k, (size, own) in held.items() for c in own], columns=["part", "cls", "n_docs", "size"])
        every = set().union(*(own for _, own in held.values()))
        price = lambda pick: sum(np.log(held[k][0]) for k in pick)
        want = min(price(pick) for n in range(8) for pick in itertools.combinations(held, n) if set().union(*(held[k][1] for k in pick)) >= every)
        assert price(ro._exact(rows)) == pytest.approx(want)
