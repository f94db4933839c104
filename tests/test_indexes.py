import numpy as np
import pytest

from aclvec.operators import generators as g
from aclvec.operators import indexes as ix
from aclvec.operators import search as se
from aclvec.operators.partitioning import role_homes, role_partition, single_partition


@pytest.fixture(scope="module")
def graph():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(600, 16)).astype(np.float32)
    return ix.Graph(x, np.arange(600), m=8, efc=64).build()


def test_graph_recall_grows_with_depth(graph):
    rng = np.random.default_rng(3)
    recall = {}
    for ef in (10, 200):
        hits = 0
        for _ in range(30):
            q = rng.normal(size=16).astype(np.float32)
            true = set(((graph.x - q) ** 2).sum(axis=1).argsort()[:10].tolist())
            hits += len(true & {n for _, n in graph.search(q, ef)[:10]})
        recall[ef] = hits / 300
    assert recall[200] >= 0.95 and recall[200] >= recall[10]


def test_walk_over_permitted_nodes_returns_only_them(graph):
    rng = np.random.default_rng(4)
    allowed = rng.random(600) < 0.3
    for two_hops in (False, True):
        found = graph.search(graph.x[5], 64, allowed, two_hops)
        assert found and all(allowed[n] for _, n in found)
    assert graph.search(graph.x[5], 64, np.zeros(600, bool)) == []


def test_graph_as_rows_and_back(graph):
    again = ix.Graph.from_rows(graph.rows("p", 0), 8)
    q = graph.x[17] + 0.01
    assert [n for _, n in again.search(q, 50)] == [n for _, n in graph.search(q, 50)]
    assert again.entry == graph.entry


@pytest.mark.parametrize("mode", ["inline", "two_hops"])
def test_shards_walk_what_the_role_set_may_see_now(spark, mode):
    """Several shards, an orphan, two role sets in one partition: each gets all that it may see and nothing else."""
    p = g.hand_h1(spark)
    v = p.docs.selectExpr("doc_id", "array(cast(doc_id as float), cast(1 as float)) as embedding")
    q = spark.createDataFrame([(1, 1, 12, [1.0, 1.0]), (2, 6, 12, [1.0, 1.0])], "query_id long, user_id long, k int, qvec array<float>")
    part, index = single_partition(p), ix.FilterGraphIndex(m=4, shard=5, mode=mode)
    found = index.search(index.build(part, v), q, p, part, 12).collect()
    assert {r.doc_id for r in found if r.query_id == 1} == {1, 2, 3, 4, 5, 6}
    assert {r.doc_id for r in found if r.query_id == 2} == {8, 9, 10, 11}


def test_lists_are_assigned_without_a_shuffle(spark):
    v = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(6)], "doc_id long, embedding array<float>")
    centroids = spark.createDataFrame([(0, [0.0, 0.0]), (1, [5.0, 0.0])], "list_id int, centroid array<double>")
    lists, _ = ix.IvfIndex(2).build(None, v, centroids)
    assert {r.doc_id: r.list_id for r in lists.collect()} == {0: 0, 1: 0, 2: 0, 3: 1, 4: 1, 5: 1}
    assert "hashpartitioning" not in lists._jdf.queryExecution().toString()


def test_fewer_evaluations_than_a_scan(graph):
    graph.evals = 0
    graph.search(graph.x[9] + 0.05, 16)
    assert graph.evals < 600


def test_results_are_filtered_against_the_present_policy(spark):
    """A document revoked after the partitions were written is never returned."""
    p = g.hand_h1(spark)
    v = p.docs.selectExpr("doc_id", "array(cast(doc_id as float), cast(1 as float)) as embedding")
    q = spark.createDataFrame([(1, 1, 10, [1.0, 1.0])], "query_id long, user_id long, k int, qvec array<float>")
    part = single_partition(p)
    now = p.but(pa=p.pa.filter("doc_id <> 2"))
    assert {r.doc_id for r in se.secure_search(q, v, now, part).collect()} == {1, 3, 4, 5, 6}


@pytest.mark.parametrize("bound", [1, 4_000_000])
@pytest.mark.parametrize("ef", [3, None])
def test_scans_keep_the_nearest_over_all_batches(spark, monkeypatch, ef, bound):
    """Many small batches with ties and two partitions in a task: the same rows as by expressions, however often a task hands on."""
    monkeypatch.setattr(se, "MAX_HELD", bound)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 4)
    try:
        p = g.hand_h1(spark)
        v = p.docs.selectExpr("doc_id", "array(cast(doc_id % 4 as float), cast(1 as float)) as embedding")
        q = spark.createDataFrame([(1, 1, 10, [1.0, 1.0]), (2, 6, 10, [0.0, 1.0])], "query_id long, user_id long, k int, qvec array<float>")
        part = role_partition(p)
        copies = part.part_doc.join(v, "doc_id").coalesce(1)
        cols = ["query_id", "rs", "part", "doc_id", "dist"]
        found = se.scan_candidates(copies, se.routed_queries(q, p, part), ef).select(cols).collect()
        plain = se.candidates(q, v, p, part, ef).select(cols).collect()
        assert len(found) and sorted(map(tuple, found)) == sorted(map(tuple, plain))
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_graphs_are_built_by_products(monkeypatch):
    """No node is searched for when it goes in, and none of the kinds of rows breaks a build: few, one, none, or copies of one vector in their thousands."""
    monkeypatch.setattr(ix.Graph, "dist", lambda *a: pytest.fail("a distance call of its own"))
    x = np.random.default_rng(6).normal(size=(3000, 16)).astype(np.float32)
    x[1000:2500] = x[7]
    for n in (0, 1, 2, 40, 3000):
        g = ix.Graph(x[:n], np.arange(n), m=8, efc=32).build()
        assert all(len(near) <= (g.m if layer else g.links0) for links in g.links for layer, near in enumerate(links))
        assert all(n != i for i, links in enumerate(g.links) for near in links for n in near)
        assert n < 2 or all(g.links[i][0] for i in range(n))


def test_own_links_are_those_of_the_nearest_before():
    x = np.random.default_rng(7).normal(size=(700, 8)).astype(np.float32)
    found = np.concatenate([ids for ids, _ in ix.earlier(x, 12)])
    for i in (0, 5, 300, 699):
        d = ((x[:i] - x[i]) ** 2).sum(axis=1)
        assert [n for n in found[i].tolist() if n >= 0] == d.argsort(kind="stable")[:12].tolist()


def test_depth_grows_until_the_floor_is_reached(spark):
    truth = spark.createDataFrame([(1, i) for i in range(8)], "query_id long, doc_id long")
    asked = []
    found, recall = ix.deepened(lambda d: asked.append(d) or truth.filter(f"doc_id < {d}"), truth, 2, 0.9, 6)
    assert asked == [2, 4, 6] and recall == 0.75 and found.count() == 6
    asked.clear()
    assert ix.deepened(lambda d: asked.append(d) or truth.filter(f"doc_id < {d}"), truth, 2, 0.5, 6)[1] == 0.5 and asked == [2, 4]


def test_answers_from_lists_are_those_of_all_candidates(spark, sf):
    from aclvec.plans.catalog_parts import mod4
    from aclvec.plans.catalog_policy import queries_n1
    from aclvec.sources.tables import vectors

    p, v, q = g.natural_n1(spark, sf), vectors(spark, sf), queries_n1(spark, sf)
    for part in (single_partition(p), role_homes(p, mod4(p))):
        for depth in (1, 3):
            index = ix.IvfIndex()
            built = tuple(x.cache() for x in index.build(part, v))
            plain = se.merge(se.permitted_only(index.search(built, q, p, part, depth), p), 10)
            assert sorted(map(tuple, index.answers(built, q, p, part, depth).collect())) == sorted(map(tuple, plain.collect()))
        index = ix.IvfPqIndex(rerank=10_000)  # all that is found is ranked again
        built = index.build(part, v)
        assert index.answers(built, q, p, part, 10).exceptAll(se.ground_truth(q, v, p)).count() == 0


def test_a_reload_that_lost_or_moved_a_row_differs(spark, sf):
    from aclvec.plans import catalog_search as cs
    from aclvec.plans.catalog_policy import queries_n1
    from aclvec.sources.tables import vectors

    p, v, q = g.natural_n1(spark, sf), vectors(spark, sf), queries_n1(spark, sf)
    index, part = ix.IvfIndex(), single_partition(p)
    lists, centroids = (x.cache() for x in index.build(part, v))
    assert cs.reload_differences(index, (lists, centroids), (lists, centroids), q, p, part) == 0
    moved = lists.selectExpr("doc_id", "if(doc_id = 3, list_id + 1, list_id) as list_id", "embedding")
    assert cs.reload_differences(index, (lists, centroids), (lists.filter("doc_id <> 3"), centroids), q, p, part) == 1
    assert cs.reload_differences(index, (lists, centroids), (moved, centroids), q, p, part) == 2
    assert cs.reload_differences(index, (lists, centroids), (lists, centroids.filter("list_id <> 0")), q, p, part) > 0
