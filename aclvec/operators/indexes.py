"""Indexes of partitions: exact, inverted lists, product-quantised lists, a layered graph and a graph that walks permitted nodes.

A partition is cut into shards of bounded size; an index is built for each shard
in one task and kept as rows. All searches return query_id, rs, part, doc_id,
dist; filtering and merging follow, and both are the same for every index.
"""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.functions.models import FilterGraphCost, GraphCost, IvfCost, ScanCost
from aclvec.functions.portable import draw_py
from aclvec.operators import scan as sc
from aclvec.operators.measures import partition_selectivity, recall_at_k
from aclvec.operators.partitioning import Partitioning
from aclvec.operators.policy import Policy, doc_classes
from aclvec.operators.search import candidates, merge, permitted_only, ranked, routed_queries

#: Vectors of one shard.
SHARD = 200_000
#: Nodes that go into a graph at once, candidates whose pairs are all compared, and cells of such a comparison.
STEP, PAIRS, CELLS = 256, 512, 1 << 21
FINITE = np.finfo(np.float32).max
SHARD_ROWS = "part string, shard int, node bigint, layer int, level int, embedding array<float>, neighbors array<int>"
FOUND = "query_id bigint, rs string, part string, doc_id bigint, dist double, evals bigint"


def level_of(vec_id: int, m: int) -> int:
    """A geometric draw by the portable hash: the same for every build."""
    u = (draw_py(vec_id, 91, 1 << 20) + 0.5) / (1 << 20)
    return int(-math.log(u) / math.log(max(2, m)))


def earlier(x: np.ndarray, k: int):
    """For each block of rows of `x`: the k nearest of the rows before each, nearest first, and their squared distances; -1 and infinity where there are fewer."""
    norms = np.einsum("ij,ij->i", x, x)[:, None]
    ask, rows = np.hstack((-2 * x, np.ones_like(norms))), np.hstack((x, norms)).T  # whose products are distances less the asking row's norm
    held = np.empty(STEP * len(x), np.float32)
    for a in range(0, len(x), STEP):
        b = min(a + STEP, len(x))
        d = np.matmul(ask[a:b], rows[:, :b], out=held[: (b - a) * b].reshape(b - a, b))
        d[:, a:][np.arange(b - a)[None] >= np.arange(b - a)[:, None]] = np.inf
        bound = np.minimum(sc.least(d, k), FINITE) if b > 2 * k else np.full(b - a, FINITE)
        at = np.flatnonzero(d <= bound[:, None])
        row, col = at // b, at % b
        counts = np.bincount(row, minlength=b - a)
        place = np.arange(len(at)) - np.repeat(np.cumsum(counts) - counts, counts)
        wide = max(k, int(counts.max(initial=0)))
        ids, far = np.full((b - a, wide), -1), np.full((b - a, wide), np.inf, np.float32)
        ids[row, place], far[row, place] = col, d[row, col]
        if wide > 2 * k:  # copies of one vector: any of them will do
            some = np.argpartition(far, 2 * k, axis=1)[:, : 2 * k]
            ids, far = np.take_along_axis(ids, some, 1), np.take_along_axis(far, some, 1)
        e = x[ids] - x[a:b, None]
        far = np.where(ids < 0, np.inf, np.einsum("ijk,ijk->ij", e, e))
        order = np.lexsort((ids, far), axis=1)[:, :k]
        yield np.take_along_axis(ids, order, 1), np.take_along_axis(far, order, 1)


def chosen(x: np.ndarray, ids: np.ndarray, d: np.ndarray, most: int) -> np.ndarray:
    """Row by row of `ids` (nearest first, -1 after the last): those nearer to the node than to one another, then the nearest of the rest, `most` in all."""
    v, lines = x[ids], np.arange(len(ids))
    norms = np.einsum("ijk,ijk->ij", v, v)
    among = None  # distances of all pairs, where these are few
    if ids.shape[1] <= PAIRS:
        among = norms[:, :, None] + norms[:, None] - 2 * (v @ v.transpose(0, 2, 1))
    taken, nearest = np.zeros(ids.shape, bool), np.where(ids < 0, -np.inf, np.inf)  # distance of every candidate to the chosen ones
    for _ in range(min(most, ids.shape[1])):
        free = ~taken & (nearest > d)
        j = free.argmax(axis=1)
        has = free[lines, j]
        if not has.any():
            break
        to = among[lines, j] if among is not None else norms + norms[lines, j][:, None] - 2 * (v @ v[lines, j][:, :, None])[:, :, 0]
        nearest = np.where(has[:, None], np.minimum(nearest, to), nearest)
        taken[lines[has], j[has]] = True
    order = np.argsort(np.where(taken, 0, np.where(ids < 0, 2, 1)), axis=1, kind="stable")[:, :most]
    return np.take_along_axis(ids, order, 1)


def linked(x: np.ndarray, efc: int, own: int, most: int) -> list[np.ndarray]:
    """Neighbours of every row of `x`: `own` of the `efc` nearest before it, and the rows that chose it, `most` in all."""
    to = np.concatenate([chosen(x, ids, d, own) for ids, d in earlier(x, efc)])
    i, j = np.nonzero(to >= 0)
    a, b = np.concatenate((i, to[i, j])), np.concatenate((to[i, j], i))
    d = np.concatenate([np.einsum("ij,ij->i", e, e) for e in (x[a[n : n + 65_536]] - x[b[n : n + 65_536]] for n in range(0, len(a), 65_536))] or [np.zeros(0)])
    order = np.lexsort((b, d, a))
    b, d, counts = b[order], d[order], np.bincount(a, minlength=len(x))
    ends = np.cumsum(counts)
    out = np.split(b, ends[:-1])
    many = np.flatnonzero(counts > most)
    many = many[np.argsort(counts[many], kind="stable")]  # rows of about one length together
    while len(many):
        some = many[-max(1, CELLS // int(counts[many[-1]]) ** (2 if counts[many[-1]] <= PAIRS else 1)) :]
        many = many[: -len(some)]
        at = (ends - counts)[some][:, None] + np.arange(counts[some].max())
        real = at < ends[some][:, None]
        at = np.where(real, at, 0)
        for n, near in zip(some.tolist(), chosen(x, np.where(real, b[at], -1), np.where(real, d[at], np.inf), most), strict=True):
            out[n] = near
    return out


class Graph:
    """A layered proximity graph over the rows of `x`."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, m: int = 16, efc: int = 64, links0: int | None = None):
        self.x, self.ids, self.m, self.efc = x, ids, m, efc
        self.links0 = links0 or 2 * m
        self.level = [level_of(int(i), m) for i in ids]
        self.links: list[list[list[int]]] = [[[] for _ in range(v + 1)] for v in self.level]
        self.entry, self.evals = 0, 0

    def build(self) -> Graph:
        """Nodes go in by their order: each chooses links among the `efc` nearest of all nodes before it, which matrix products find. Links back are cut to the bound when all are in."""
        level = np.array(self.level)
        for layer in range(int(level.max(initial=-1)) + 1):
            nodes = np.flatnonzero(level >= layer)
            most, own = (self.m, self.m) if layer else (self.links0, self.links0 // 2)
            for i, near in zip(nodes.tolist(), linked(self.x[nodes], self.efc, own, most), strict=True):
                self.links[i][layer] = nodes[near].tolist()
        self.entry = int(level.argmax()) if len(level) else 0
        return self

    def dist(self, q: np.ndarray, nodes: list[int]) -> np.ndarray:
        self.evals += len(nodes)
        d = self.x[nodes] - q
        return np.einsum("ij,ij->i", d, d)

    def descend(self, q: np.ndarray, at: int, top: int, bottom: int) -> int:
        """Greedy steps from layer `top` to above `bottom`."""
        best = float(self.dist(q, [at])[0])
        for layer in range(top, bottom, -1):
            moved = True
            while moved:
                moved = False
                near = self.links[at][layer] if layer < len(self.links[at]) else []
                if near:
                    d = self.dist(q, near)
                    j = int(d.argmin())
                    if d[j] < best:
                        best, at, moved = float(d[j]), near[j], True
        return at

    def beam(self, q: np.ndarray, starts: list[int], ef: int, layer: int, allowed: np.ndarray | None = None, two_hops: bool = False) -> list[tuple[float, int]]:
        """The ef nearest found from `starts`; with `allowed`, only permitted nodes are kept and walked (or, with `two_hops`, reached over forbidden ones)."""
        seen = set(starts)
        d = self.dist(q, starts).tolist()
        open_ = list(zip(d, starts, strict=True))
        heapq.heapify(open_)
        kept = [(-a, b) for a, b in open_ if allowed is None or allowed[b]]
        heapq.heapify(kept)
        while open_:
            near, at = heapq.heappop(open_)
            if len(kept) >= ef and near > -kept[0][0]:
                break
            new = []
            for n in self.links[at][layer] if layer < len(self.links[at]) else []:
                if n in seen:
                    continue
                seen.add(n)
                if allowed is None or allowed[n]:
                    new.append(n)
                elif two_hops:
                    for h in self.links[n][layer] if layer < len(self.links[n]) else []:
                        if h not in seen and allowed[h]:
                            seen.add(h)
                            new.append(h)
            if not new:
                continue
            for dn, n in zip(self.dist(q, new).tolist(), new, strict=True):
                if len(kept) < ef or dn < -kept[0][0]:
                    heapq.heappush(open_, (dn, n))
                    heapq.heappush(kept, (-dn, n))
                    if len(kept) > ef:
                        heapq.heappop(kept)
        return sorted((-a, b) for a, b in kept)

    def search(self, q: np.ndarray, ef: int, allowed: np.ndarray | None = None, two_hops: bool = False) -> list[tuple[float, int]]:
        if not len(self.ids):
            return []
        at = self.descend(q, self.entry, self.level[self.entry], 0)
        starts = [at]
        if allowed is not None:  # walks begin at permitted nodes: the nearest of a few of them
            good = np.flatnonzero(allowed)
            if not len(good):
                return []
            few = good[:: max(1, len(good) // 32)][:32].tolist()
            d = self.dist(q, few)
            starts = sorted({at} | {few[j] for j in np.argsort(d)[:4].tolist()})
        return self.beam(q, starts, ef, 0, allowed, two_hops)

    def rows(self, part: str, shard: int) -> pd.DataFrame:
        out = [(part, shard, int(self.ids[i]), layer, self.level[i], self.x[i].tolist() if layer == 0 else None, links) for i in range(len(self.ids)) for layer, links in enumerate(self.links[i])]
        return pd.DataFrame(out, columns=["part", "shard", "node", "layer", "level", "embedding", "neighbors"])

    @classmethod
    def from_rows(cls, rows: pd.DataFrame, m: int = 16) -> Graph:
        rows = rows.sort_values(["node", "layer"])
        base = rows[rows["layer"] == 0]
        out = cls(np.array(base["embedding"].tolist(), np.float32), base["node"].to_numpy(), m)
        at = {n: i for i, n in enumerate(base["node"])}
        for n, layer, near in zip(rows["node"], rows["layer"], rows["neighbors"], strict=True):
            out.links[at[n]][layer] = [int(v) for v in near]
        out.entry = max(range(len(out.ids)), key=lambda i: (out.level[i], -i)) if len(out.ids) else 0
        return out


def with_shards(part: Partitioning, vectors: DataFrame, shard: int = SHARD) -> DataFrame:
    """part, shard, node, embedding: copies of vectors, partitions cut by a hash into shards of about `shard` rows."""
    sizes = part.sizes().select("part", F.ceil(F.col("n_docs") / shard).cast("int").alias("n_shards"))
    rows = part.part_doc.join(sizes, "part").join(vectors.select("doc_id", "embedding"), "doc_id")
    return rows.select("part", F.pmod(F.xxhash64(F.lit(5), "doc_id"), "n_shards").cast("int").alias("shard"), F.col("doc_id").alias("node"), "embedding")


@dataclass(frozen=True)
class ExactIndex:
    """No index: every vector of a searched partition is compared."""

    depth_name = "none"

    def cost_model(self):
        return ScanCost()

    def build(self, part: Partitioning, vectors: DataFrame) -> DataFrame:
        return vectors

    def search(self, built: DataFrame, queries: DataFrame, p: Policy, part: Partitioning, depth: int | None) -> DataFrame:
        return candidates(queries, built, p, part, depth).withColumn("evals", F.lit(1).cast("long"))

    def answers(self, built: DataFrame, queries: DataFrame, p: Policy, part: Partitioning, depth: int | None, k: int = 10) -> DataFrame:
        """The merged and permitted answers of `search`, without its lists of `depth` candidates."""
        return sc.secure_search(queries, built, p, part, depth, k)


@dataclass(frozen=True)
class HnswIndex:
    """The layered graph, filtered after the search."""

    m: int = 16
    efc: int = 64
    shard: int = SHARD
    widen: int = 1
    mode: str = "post"
    depth_name = "ef"

    def cost_model(self):
        return GraphCost()

    def build(self, part: Partitioning, vectors: DataFrame) -> DataFrame:
        """SHARD_ROWS of every shard's graph; nodes go in by id, so a rebuild gives the same graph.

        The frame is lazy and a search reads it more than once: `persist` and `load` it first.
        """
        m, efc, links0 = self.m, self.efc, 2 * self.m * self.widen

        def make(key, rows):
            rows = rows.sort_values("node")
            graph = Graph(np.array(rows["embedding"].tolist(), np.float32), rows["node"].to_numpy(), m, efc, links0).build()
            return graph.rows(*key)

        rows = with_shards(part, vectors, self.shard)
        n_shards = part.sizes().agg(F.sum(F.ceil(F.col("n_docs") / self.shard))).first()[0] or 1
        # a build costs far more than its bytes tell, so the number of tasks is not left to their size
        n_tasks = max(int(n_shards), rows.sparkSession.sparkContext.defaultParallelism)
        return rows.repartition(n_tasks, "part", "shard").groupBy("part", "shard").applyInPandas(make, SHARD_ROWS)

    def search(self, built: DataFrame, queries: DataFrame, p: Policy, part: Partitioning, depth: int) -> DataFrame:
        """Queries go to the shards; graphs stay where they are. Each shard returns its `depth` nearest.

        To filter during the walk, a shard also gets one row for each of its nodes
        with the access class that the document has now: no more than the shard
        holds, however many documents a role set may see.
        """
        shards = built.select(F.col("part").alias("part"), F.col("shard").alias("shard")).distinct()
        asked = routed_queries(queries, p, part).join(shards, "part")
        inline, two_hops, m = self.mode != "post", self.mode == "two_hops", self.m
        asked = asked.select(F.col("part").alias("part"), F.col("shard").alias("shard"), F.lit(False).alias("is_node"), F.col("query_id").alias("id"), F.col("rs").alias("key"), F.col("qvec").alias("qvec"))
        if inline:
            nodes = built.filter("layer = 0").join(asked.select("part").distinct(), "part", "left_semi").select("part", "shard", "node")
            classes = nodes.join(doc_classes(p).select(F.col("doc_id").alias("node"), "cls"), "node")
            asked = asked.unionByName(classes.select("part", "shard", F.lit(True).alias("is_node"), F.col("node").alias("id"), F.col("cls").alias("key")), allowMissingColumns=True)

        def run(key, asked, rows):
            cols = ["query_id", "rs", "part", "doc_id", "dist", "evals"]
            questions = asked[~asked["is_node"]]
            if not len(questions) or not len(rows):
                return pd.DataFrame(columns=cols)
            graph, out, allowed = Graph.from_rows(rows, m), [], dict.fromkeys(questions["key"])
            if inline:
                nodes = asked[asked["is_node"]].drop_duplicates("id")
                codes, names = pd.factorize(nodes.set_index("id")["key"].reindex(graph.ids))
                for rs in allowed:  # the last entry is for nodes that nobody may see, whose code is -1
                    allowed[rs] = np.array([not set(rs.split(",")).isdisjoint(c.split(",")) for c in names] + [False])[codes]
            for q in questions.itertuples():
                graph.evals = 0
                found = graph.search(np.array(q.qvec, np.float32), depth, allowed[q.key], two_hops)
                out += [(q.id, q.key, key[0], int(graph.ids[n]), float(d), graph.evals) for d, n in found]
            return pd.DataFrame(out, columns=cols)

        return asked.groupBy("part", "shard").cogroup(built.groupBy("part", "shard")).applyInPandas(run, FOUND)


    def answers(self, built: DataFrame, queries: DataFrame, p: Policy, part: Partitioning, depth: int, k: int = 10) -> DataFrame:
        """The merged and permitted answers of `search`."""
        return merge(permitted_only(self.search(built, queries, p, part, depth), p), k)

    def deepest(self, part: Partitioning) -> int:
        """A depth beyond which nothing is left to find."""
        return part.sizes().agg(F.max("n_docs")).first()[0] or 1


@dataclass(frozen=True)
class FilterGraphIndex(HnswIndex):
    """The graph with wider neighbour lists that walks permitted nodes during the search (mode `inline`), or looks two hops far over forbidden ones (`two_hops`)."""

    widen: int = 3
    mode: str = "inline"

    def cost_model(self):
        return FilterGraphCost(width=12.0)


@dataclass(frozen=True)
class IvfIndex:
    """Inverted lists: vectors by their nearest of `nlist` centroids, learned by k-means on the vectors or given."""

    nlist: int = 10
    seed: int = 3
    depth_name = "nprobe"

    def cost_model(self):
        return IvfCost(self.nlist)

    def centroids(self, vectors: DataFrame) -> DataFrame:
        """list_id, centroid."""
        from pyspark.ml.clustering import KMeans
        from pyspark.ml.functions import array_to_vector

        model = KMeans(k=self.nlist, seed=self.seed, maxIter=10, featuresCol="f").fit(vectors.select(array_to_vector("embedding").alias("f")))
        rows = [(i, [float(v) for v in c]) for i, c in enumerate(model.clusterCenters())]
        return vectors.sparkSession.createDataFrame(rows, "list_id int, centroid array<double>")

    def build(self, part: Partitioning, vectors: DataFrame, centroids: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
        """(doc_id, embedding, list_id) and the centroids. Centroids are one row of `nlist` entries, so vectors are not shuffled."""
        from aclvec.functions.vector import l2sq

        centroids = self.centroids(vectors) if centroids is None else centroids
        one = centroids.agg(F.collect_list(F.struct("list_id", "centroid")).alias("centroids"))
        near = F.array_min(F.transform("centroids", lambda c: F.struct(l2sq("embedding", c["centroid"]).alias("d"), c["list_id"].alias("list_id"))))
        return vectors.join(F.broadcast(one)).select("doc_id", near["list_id"].alias("list_id"), "embedding"), centroids

    def probes(self, queries: DataFrame, centroids: DataFrame, nprobe: int) -> DataFrame:
        """The queries with each of the nprobe nearest lists."""
        from pyspark.sql.window import Window

        from aclvec.functions.vector import l2sq

        w = Window.partitionBy("query_id", "part").orderBy(F.round("cd", 6), "list_id")
        rows = queries.join(F.broadcast(centroids)).withColumn("cd", l2sq("centroid", "qvec")).withColumn("probe", F.row_number().over(w))
        return rows.filter(F.col("probe") <= nprobe).drop("centroid", "cd")

    def search(self, built: tuple[DataFrame, DataFrame], queries: DataFrame, p: Policy, part: Partitioning, depth: int) -> DataFrame:
        from aclvec.functions.vector import l2sq

        lists, centroids = built
        asked = self.probes(routed_queries(queries, p, part), centroids, depth)
        rows = part.part_doc.join(lists, "doc_id").join(asked, ["part", "list_id"])
        return rows.select("query_id", "rs", "part", "doc_id", l2sq("embedding", "qvec").alias("dist"), F.lit(1).cast("long").alias("evals"))

    def answers(self, built: tuple[DataFrame, DataFrame], queries: DataFrame, p: Policy, part: Partitioning, depth: int, k: int = 10) -> DataFrame:
        """The merged and permitted answers of `search`, without a row for each candidate: lists are compared by matrix products where they lie."""
        lists, centroids = built
        asked = self.probes(routed_queries(queries, p, part), centroids, depth)
        return merge(nearest_in_lists(lists, asked, part, k, p), k)

    def deepest(self, part: Partitioning) -> int:
        return self.nlist


def nearest_in_lists(lists: DataFrame, asked: DataFrame, part: Partitioning, k: int, p: Policy | None = None, books: np.ndarray | None = None) -> DataFrame:
    """query_id, rs, part, doc_id, dist: the k nearest rows of the probed lists in each partition; with a policy, of those that the role set may see.

    lists: doc_id, list_id, embedding; with `books`, code in its place, and distances are to the vectors that codes stand for.
    """
    copies = part.part_doc.join(lists, "doc_id")
    key = F.concat("part", F.lit(f"/{sc.ALL}"))
    if p is not None:
        copies, key = copies.join(doc_classes(p).select("doc_id", "cls"), "doc_id"), F.concat_ws("/", "part", "cls")
    copies = copies.select(key.alias("key"), "doc_id", F.col("embedding" if books is None else "code").alias("embedding"), "list_id")
    per_query = asked.groupBy("query_id", "rs", "part").agg(F.first("qvec").alias("qvec"), F.collect_list("list_id").alias("probes"), F.lit(k).alias("k"))

    def decoded(column) -> np.ndarray:
        codes = np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), len(books))
        return books[np.arange(len(books))[None], codes].reshape(len(codes), -1).astype(np.float64)

    found = sc.scan(sc.dealt(copies, part.part_doc.count()), per_query, decoded=sc.matrix if books is None else decoded)
    return ranked(found, k, ("query_id", "part")).select("query_id", "rs", "part", "doc_id", "dist")


@dataclass(frozen=True)
class IvfPqIndex:
    """Inverted lists of product-quantised codes; the best by their codes are ranked again exactly.

    A depth beyond the number of lists probes all of them and ranks as many times `rerank` again.
    """

    nlist: int = 10
    m: int = 8
    codes: int = 16
    rerank: int = 100
    seed: int = 3
    depth_name = "nprobe"

    def cost_model(self):
        return IvfCost(self.nlist)

    def codebooks(self, vectors: DataFrame, sample: int = 20_000, rounds: int = 10) -> np.ndarray:
        """(m, codes, d / m): k-means of each slice on a bounded sample."""
        n = vectors.count()
        share = min(1.0, sample / max(1, n))
        rows = vectors.filter(F.pmod(F.xxhash64(F.lit(9), "doc_id"), F.lit(1 << 20)) <= int(share * (1 << 20))).select("doc_id", "embedding").orderBy("doc_id").toPandas()
        x = np.array(rows["embedding"].tolist(), np.float32)
        rng, out = np.random.default_rng(self.seed), []
        for part in np.split(x, self.m, axis=1):
            c = part[rng.choice(len(part), min(self.codes, len(part)), replace=False)]
            for _ in range(rounds):
                near = ((part[:, None] - c[None]) ** 2).sum(axis=2).argmin(axis=1)
                c = np.stack([part[near == j].mean(axis=0) if (near == j).any() else c[j] for j in range(len(c))])
            out.append(c)
        return np.stack(out)

    def build(self, part: Partitioning, vectors: DataFrame):
        lists, centroids = IvfIndex(self.nlist, self.seed).build(part, vectors)
        books = self.codebooks(vectors)

        def encode(frames):
            for f in frames:
                x = np.array(f["embedding"].tolist(), np.float32).reshape(len(f), -1)
                codes = np.stack([((s[:, None] - b[None]) ** 2).sum(axis=2).argmin(axis=1) for s, b in zip(np.split(x, len(books), axis=1), books, strict=True)], axis=1).astype(np.uint8)
                yield pd.DataFrame({"doc_id": f["doc_id"], "list_id": f["list_id"], "code": [c.tobytes() for c in codes]})

        return lists.mapInPandas(encode, "doc_id bigint, list_id int, code binary"), centroids, books, vectors

    def search(self, built, queries: DataFrame, p: Policy, part: Partitioning, depth: int) -> DataFrame:
        return self._search(built, queries, p, part, depth, None)

    def _search(self, built, queries: DataFrame, p: Policy, part: Partitioning, depth: int, policy: Policy | None) -> DataFrame:
        from aclvec.functions.vector import l2sq

        codes, centroids, books, vectors = built
        asked = IvfIndex(self.nlist).probes(routed_queries(queries, p, part), centroids, depth)
        best = nearest_in_lists(codes, asked, part, self.rerank * max(self.nlist, depth) // self.nlist, policy, books)
        again = best.join(queries.select("query_id", "qvec"), "query_id").join(vectors.select("doc_id", "embedding"), "doc_id")
        return again.select("query_id", "rs", "part", "doc_id", l2sq("embedding", "qvec").alias("dist"), F.lit(1).cast("long").alias("evals"))

    def answers(self, built, queries: DataFrame, p: Policy, part: Partitioning, depth: int, k: int = 10) -> DataFrame:
        """The merged answers; what is ranked again are the best that the role set may see, not the best of all, so that the filter leaves no gaps."""
        return merge(permitted_only(self._search(built, queries, p, part, depth, p), p), k)

    def deepest(self, part: Partitioning) -> int:
        return self.nlist * -(-(part.sizes().agg(F.max("n_docs")).first()[0] or 1) // self.rerank)


def deepened(answers, truth: DataFrame, depth: int, floor: float, deepest: int) -> tuple[DataFrame, float]:
    """The answers (cached) and their recall at `depth`, or at the first double of it that reaches `floor`; `answers(depth)` runs one search of all queries."""
    while True:
        found = answers(depth).cache()
        recall = recall_at_k(found, truth).agg(F.avg("recall")).first()[0]
        if recall >= floor or depth >= deepest:
            return found, recall
        found.unpersist()
        depth = min(2 * depth, deepest)


def choose_index(p: Policy, part: Partitioning) -> DataFrame:
    """part, kind: a plain graph where every reader may see the whole partition, else the one that walks permitted nodes."""
    return partition_selectivity(p, part).groupBy("part").agg(F.when(F.bool_and(F.col("permitted") == F.col("n_docs")), "hnsw").otherwise("filtergraph").alias("kind"))


def persist(built, path: str) -> None:
    """Writes a built index under `path`: shards of graphs in directories by partition, lists, centroids and codebooks in folders of their own.

    The vectors that `ExactIndex` and the second ranking of `IvfPqIndex` read are the caller's and are not copied.
    """
    parts = built if isinstance(built, tuple) else (built,)
    for i, x in enumerate(parts[:3]):
        if isinstance(x, np.ndarray):
            centres = [(s, c, x[s, c].astype(float).tolist()) for s in range(x.shape[0]) for c in range(x.shape[1])]  # m x codes rows
            x = parts[0].sparkSession.createDataFrame(centres, "slice int, code int, centre array<double>")
        writer = x.write.mode("overwrite")
        (writer.partitionBy("part") if "part" in x.columns else writer).parquet(f"{path}/{i}")


def load(index, spark: SparkSession, path: str, vectors: DataFrame):
    """What `index.build` returned, from what `persist` wrote; `vectors`: those that it was built for."""
    if isinstance(index, ExactIndex):
        return vectors
    if isinstance(index, HnswIndex):
        names = [f.split()[0] for f in SHARD_ROWS.split(", ")]
        return spark.read.schema(SHARD_ROWS).parquet(f"{path}/0").select(*names)
    lists, centroids = (spark.read.parquet(f"{path}/{i}") for i in range(2))
    if isinstance(index, IvfIndex):
        return lists, centroids
    rows = spark.read.parquet(f"{path}/2").orderBy("slice", "code").collect()  # m x codes rows
    books = np.array([r.centre for r in rows]).reshape(1 + rows[-1].slice, 1 + rows[-1].code, -1)
    return lists, centroids, books.astype(np.float32), vectors


INDEXES = {"exact": ExactIndex, "hnsw": HnswIndex, "filtergraph": FilterGraphIndex, "ivf": IvfIndex, "ivfpq": IvfPqIndex}
