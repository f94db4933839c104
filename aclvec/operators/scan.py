"""Exact scans of many queries by matrix products in Arrow batches: the nearest that each query may see, and places in a partition.

Products only choose what is compared again: every distance that is returned, or
that decides an order, is summed anew dimension by dimension, as the expressions
of `functions.vector` do. Queries of a block go to every task; a task hands on
what its rows add to each query, so a table of any size is scanned where it lies.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from aclvec.operators import search as se
from aclvec.operators.partitioning import Partitioning
from aclvec.operators.policy import Policy, doc_classes

#: Rows compared at once, queries compared at once, and rows that a task gets about.
CHUNK, BLOCK, TASK_ROWS = 16_384, 256, 100_000
#: Rows that are sent to every task where queries outnumber them.
SENT = 200_000
#: Rows of a piece whose distances stay in a core's cache.
PIECE = 2_048
#: Rows whose places are counted together, and distances of rows to marks that are looked at together.
WIDE, MARKED = 16_384, 4_000_000
#: More than rounding to six places and the products' error can move a distance.
NEAR = 1.5e-6
#: Stands for the class of rows that are not filtered.
ALL = "*"


def dealt(copies: DataFrame, n_rows: int) -> DataFrame:
    """Rows dealt to enough tasks, as many for each core: a scan costs far more than its bytes tell."""
    cores = copies.sparkSession.sparkContext.defaultParallelism
    return copies.repartition(cores * max(1, -(-n_rows // (TASK_ROWS * cores))), "doc_id")


def blocks(asked: DataFrame) -> list[DataFrame]:
    """`asked` in blocks of queries that may be sent to every task."""
    n = -(-asked.count() // se.MAX_BROADCAST_QUERIES)
    n = 2 * n if n > 1 else 1  # room for uneven blocks
    return [asked] if n == 1 else [asked.filter(F.pmod(F.xxhash64(F.lit(43), "query_id"), F.lit(n)) == i) for i in range(n)]


def matrix(column) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1)


def exact(q: np.ndarray, x: np.ndarray, qi: np.ndarray, ri: np.ndarray) -> np.ndarray:
    """Squared distances of pairs, summed in the order of the dimensions."""
    out = np.zeros(len(qi))
    for a in range(0, len(qi), PIECE):
        e = x[ri[a : a + PIECE]] - q[qi[a : a + PIECE]]
        d = out[a : a + PIECE]
        for one in np.ascontiguousarray((e * e).T):
            d += one
    return out


def within(asks: np.ndarray, cols: np.ndarray, line: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each product that is at most the query's line: query, column, product."""
    found = []
    for lo in range(0, cols.shape[1], PIECE):
        d = asks @ cols[:, lo : lo + PIECE]
        some = np.flatnonzero(np.fmin.reduce(d, axis=1) <= line[:, 0])  # most queries have none
        if len(some):
            d = d[some]
            n, r = np.divmod(np.flatnonzero(d <= line[some]), d.shape[1])
            found.append((some[n], r + lo, d[n, r]))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def error(q: np.ndarray, x2: np.ndarray, kind) -> float:
    """More than products of this kind can be off from any squared distance of q to rows with the squared norms x2."""
    size = np.sqrt((q * q).sum(axis=1).max(initial=0)) + np.sqrt(x2.max(initial=0))
    return float(2 * (q.shape[1] + 8) * np.finfo(kind).eps * size * size)


def spread(x: np.ndarray, x2: np.ndarray) -> float:
    """Mean squared distance of rows from their mean."""
    return float(x2.mean() - (x.mean(axis=0) ** 2).sum()) if len(x) else 0.0


def kind_for(q: np.ndarray, x2: np.ndarray, apart: float):
    """Single precision where its error is far below the `spread` of the rows, else double."""
    return np.float32 if error(q, x2, np.float32) <= 1e-3 * apart else np.float64


def turned(x: np.ndarray, x2: np.ndarray, kind) -> np.ndarray:
    """Rows as columns whose products with `asking` are distances less the query's squared norm."""
    out = np.empty((x.shape[1] + 1, len(x)), kind)
    out[:-1], out[-1] = x.T, x2
    return out


def asking(q: np.ndarray, kind) -> np.ndarray:
    return np.hstack((-2 * q, np.ones((len(q), 1)))).astype(kind)


def least(d: np.ndarray, k: int) -> np.ndarray:
    """For each row a bound that its k least cells do not exceed, and few others: the k-th least of the minima of groups of cells."""
    groups = d.shape[1] // max(1, min(64, d.shape[1] // (4 * k)))
    cut = d.shape[1] // groups * groups
    low = d[:, :cut].reshape(len(d), -1, groups).min(axis=1)
    return np.partition(low, k - 1, axis=1)[:, k - 1]


def chunks(batches):
    """Columns key, doc_id, embedding (and others) in chunks of about CHUNK rows."""
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= CHUNK:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held)


def opened(table, decoded=matrix) -> tuple[np.ndarray, list[str], np.ndarray, np.ndarray, np.ndarray]:
    """Codes and names of the keys, ids, vectors and their squared norms."""
    keys = table.column(0).combine_chunks().dictionary_encode()
    x = decoded(table.column(2))
    return keys.indices.to_numpy(), keys.dictionary.to_pylist(), table.column(1).to_numpy(), x, (x * x).sum(axis=1)


def meets(row: str, ask: str) -> bool:
    """Whether a role set that asks `part/roles` may see rows of `part/class`."""
    (a, cls), (b, rs) = row.rsplit("/", 1), ask.rsplit("/", 1)
    return a == b and (cls == ALL or not set(cls.split(",")).isdisjoint(rs.split(",")))


def scan(copies: DataFrame, asked: DataFrame, by_document: bool = False, decoded=matrix) -> DataFrame:
    """query_id, rs, part, doc_id, dist, k: for each asked partition the k nearest rows that the role set may see, and at most a few more from every task.

    copies: key (`part/class`), doc_id, embedding; asked: query_id, rs, part, k,
    qvec. With `by_document`, documents own several rows and the best counts.
    With a column list_id in copies and probes (an array of lists) in asked, a query
    is compared with rows of its lists alone. `decoded` makes vectors of the column embedding.
    """
    found = None
    for some in blocks(asked):
        one = _scan(copies, some, by_document, decoded)
        found = one if found is None else found.unionByName(one)
    return found


def _scan(copies: DataFrame, asked: DataFrame, by_document: bool, decoded) -> DataFrame:
    in_lists = ["probes"] if "probes" in asked.columns else []
    rows = asked.select("query_id", "rs", "part", F.col("k").cast("int").alias("k"), F.col("qvec").cast("array<double>").alias("qvec"), *in_lists).toArrow()
    groups: dict[tuple[str, str], list[int]] = {}
    for i, key in enumerate(zip(rows.column("part").to_pylist(), rows.column("rs").to_pylist(), strict=True)):
        groups.setdefault(key, []).append(i)
    ids, limits = rows.column("query_id").to_numpy(), rows.column("k").to_numpy()
    q = matrix(rows.column("qvec")) if len(ids) else np.zeros((0, 1))
    probed = None
    if in_lists:
        probes = rows.column("probes").to_pylist()
        probed = np.zeros((len(probes), 1 + max(map(max, filter(None, probes)), default=0)), bool)
        for i, some in enumerate(probes):
            probed[i, some] = True
    sent = copies.sparkSession.sparkContext.broadcast({g: (ids[at], limits[at].astype(np.int64), q[at], probed[at] if in_lists else None) for g, at in groups.items()})
    bound = se.MAX_HELD
    schema = pa.schema([("query_id", pa.int64()), ("rs", pa.string()), ("part", pa.string()), ("doc_id", pa.int64()), ("dist", pa.float64()), ("k", pa.int32())])

    def first(n, docs, d, limit):
        """The first of each query by rounded distance, then id."""
        if by_document:
            order = np.lexsort((d, docs, n))
            n, docs, d = n[order], docs[order], d[order]
            keep = np.ones(len(n), bool)
            keep[1:] = (n[1:] != n[:-1]) | (docs[1:] != docs[:-1])
            n, docs, d = n[keep], docs[keep], d[keep]
        order = np.lexsort((docs, np.round(d, 6), n))
        n, docs, d = n[order], docs[order], d[order]
        keep = np.arange(len(n)) - np.searchsorted(n, n) < limit[n]
        return n[keep], docs[keep], d[keep]

    def emit(held):
        for (g, at), (n, docs, d, _) in held.items():
            if len(n):
                ids, limit, _, _ = sent.value[g]
                yield pa.RecordBatch.from_arrays([
                    pa.array(ids[at + n], pa.int64()), pa.array([g[1]] * len(n), pa.string()), pa.array([g[0]] * len(n), pa.string()),
                    pa.array(docs, pa.int64()), pa.array(d, pa.float64()), pa.array(limit[at + n], pa.int32()),
                ], schema=schema)

    def run(batches):
        held: dict = {}  # by group and block: query, doc_id, distance, and the worst distance that is still wanted
        seen: dict[tuple[str, tuple], bool] = {}
        for table in chunks(batches):
            codes, names, docs, x, norms = opened(table, decoded)
            whole, apart = {}, spread(x, norms)
            if by_document:
                order = np.argsort(docs, kind="stable")
                codes, docs, x, norms = codes[order], docs[order], x[order], norms[order]
            of_part: dict[str, list[int]] = {}
            for i, name in enumerate(names):
                of_part.setdefault(name.rsplit("/", 1)[0], []).append(i)
            lists = table.column(3).to_numpy() if in_lists else None
            for g, (_, limits, q, probed) in sent.value.items():
                visible = np.zeros(len(names), bool)
                for i in of_part.get(g[0], ()):
                    k = names[i]
                    visible[i] = seen.setdefault((k, g), meets(k, f"{g[0]}/{g[1]}")) if (k, g) not in seen else seen[k, g]
                if not visible.any():
                    continue
                at = np.flatnonzero(visible[codes])
                pieces = [(None, 0, len(at))]
                if by_document:
                    starts = np.flatnonzero(np.r_[True, docs[at][1:] != docs[at][:-1]])
                elif in_lists:
                    at = at[np.argsort(lists[at], kind="stable")]
                    cuts = np.flatnonzero(np.r_[True, lists[at][1:] != lists[at][:-1], True]).tolist()
                    pieces = [(int(lists[at[i]]), i, j) for i, j in zip(cuts, cuts[1:], strict=False) if lists[at[i]] < probed.shape[1]]
                ids, every, cols = docs[at], len(at) == len(docs), {}
                for b in range(0, len(q), BLOCK):
                    some, limit = q[b : b + BLOCK], limits[b : b + BLOCK]
                    q2 = (some * some).sum(axis=1)
                    none = np.zeros(0, np.int64)
                    old_n, old_docs, old_d, worst = held.get((g, b), (none, none, np.zeros(0), np.full(len(some), np.inf)))
                    most, hits = int(limit.max()), [(none, none)]
                    kind = kind_for(some, norms, apart)
                    if kind not in whole:
                        whole[kind] = turned(x, norms, kind)
                    if kind not in cols:
                        cols[kind] = whole[kind] if every and not in_lists else whole[kind][:, at]
                    off, asks = NEAR + error(some, norms, kind), asking(some, kind)
                    for one, i, j in pieces:
                        who = np.arange(len(some)) if one is None else np.flatnonzero(probed[b : b + BLOCK, one])
                        if not np.isfinite(worst[who]).all():
                            best = asks[who] @ cols[kind][:, i:j]
                            best = np.minimum.reduceat(best, starts, axis=1) if by_document else best
                            if most < best.shape[1]:
                                worst[who] = np.minimum(worst[who], np.partition(best, most - 1, axis=1)[:, most - 1] + q2[who] + off)
                        line = np.nextafter((worst[who] - q2[who] + off).astype(kind), kind(np.inf))
                        n, r, _ = within(asks[who], cols[kind][:, i:j], line[:, None])
                        hits.append((who[n], i + r))
                    n, r = (np.concatenate(h) for h in zip(*hits, strict=True))
                    n, found, far = first(np.r_[old_n, n], np.r_[old_docs, ids[r]], np.r_[old_d, exact(some, x, n, at[r])], limit)
                    worst = np.full(len(some), np.inf)
                    counts = np.bincount(n, minlength=len(some))
                    full = np.flatnonzero(counts >= limit)
                    last = np.cumsum(counts) - 1
                    worst[full] = far[last[full]] + NEAR if len(far) else np.inf
                    held[g, b] = (n, found, far, worst)
            if sum(len(h[0]) for h in held.values()) > bound:
                yield from emit(held)
                held = {}
        yield from emit(held)

    return copies.select("key", "doc_id", "embedding", *(["list_id"] if in_lists else [])).mapInArrow(run, "query_id bigint, rs string, part string, doc_id bigint, dist double, k int")


def knn(queries: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """`search.knn` by squared distance."""
    asked = queries.select("query_id", F.lit("").alias("rs"), F.lit("").alias("part"), F.lit(k).alias("k"), "qvec")
    copies = dealt(vectors.select(F.lit(f"/{ALL}").alias("key"), "doc_id", "embedding"), vectors.count())
    return se.ranked(scan(copies, asked), k).select("query_id", "rank", "doc_id", F.round("dist", 6).alias("dist"))


def ground_truth(queries: DataFrame, vectors: DataFrame, p: Policy, k: int | None = None, by_document: bool = False) -> DataFrame:
    """`search.ground_truth` (and, by document, `search.top_documents`) by squared distance: rows meet role sets by access class."""
    sets = queries.join(se.query_role_sets(queries, p), "user_id")
    asked = sets.select("query_id", "rs", F.lit("").alias("part"), (F.col("k") if k is None else F.lit(k)).alias("k"), "qvec")
    key = F.concat(F.lit("/"), "cls").alias("key")
    copies = vectors.select("doc_id", "embedding").join(doc_classes(p).select("doc_id", key), "doc_id")
    found = scan(dealt(copies, vectors.count()), asked, by_document)
    if by_document:
        found = found.groupBy("query_id", "doc_id", "k").agg(F.min("dist").alias("dist"))
    return se.ranked(found, F.col("k")).select("query_id", "rank", "doc_id", F.round("dist", 6).alias("dist"))


def candidates(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, ef: int) -> DataFrame:
    """`search.candidates` at a depth, by squared distance: nothing is filtered yet."""
    asked = se.routed_queries(queries, p, part).withColumn("k", F.lit(ef))
    key = F.concat("part", F.lit(f"/{ALL}")).alias("key")
    copies = part.part_doc.join(vectors.select("doc_id", "embedding"), "doc_id").select(key, "doc_id", "embedding")
    return se.ranked(scan(dealt(copies, part.part_doc.count()), asked), ef, ("query_id", "part")).select("query_id", "rs", "part", "doc_id", "dist")


def places(vectors: DataFrame, part: Partitioning, marks: DataFrame) -> DataFrame:
    """query_id, part, doc_id, place: how many rows of the partition lie before each marked document, plus 1.

    marks: query_id, part, doc_id, dist (rounded to six places), qvec; the document is in the partition. Rows are ordered by rounded distance, then id.
    A row meets a query once, in however many of the query's partitions it lies.
    """
    homes = part.part_doc.groupBy("doc_id").agg(F.array_join(F.array_sort(F.collect_list("part")), "\n").alias("key"))
    copies, found = dealt(vectors.select("doc_id", "embedding").join(homes, "doc_id").select("key", "doc_id", "embedding"), vectors.count()), None
    per_query = marks.groupBy("query_id").agg(F.first("qvec").cast("array<double>").alias("qvec"), F.collect_list(F.struct("part", "doc_id", "dist")).alias("m"))
    per_query = per_query.select("query_id", "qvec", F.col("m.part").alias("parts"), F.col("m.doc_id").alias("docs"), F.col("m.dist").alias("dists")).persist()
    for some in blocks(per_query):
        one = _places(copies, some)
        found = one if found is None else found.unionByName(one)
    per_query.unpersist()
    return found.groupBy("query_id", "part", "doc_id").agg((F.sum("n") + 1).alias("place"))


def _marked(rows) -> list[tuple]:
    """Blocks of queries that ask about the same partitions, or a few kinds of them: ids, vectors, and by partition the queries and their marks in order.

    Of a block's queries `at` has those with marks in the partition; dists and docs are filled up with infinity and 0, `n` says how many count.
    """
    ids, q = rows.column("query_id").to_numpy(), matrix(rows.column("qvec")) if rows.num_rows else np.zeros((0, 1))
    parts, docs, dists = (rows.column(c).combine_chunks() for c in ("parts", "docs", "dists"))
    owner = np.repeat(np.arange(len(ids)), np.diff(parts.offsets.to_numpy()))
    coded = parts.flatten().dictionary_encode()
    codes, names = coded.indices.to_numpy(), coded.dictionary.to_pylist()
    docs, dists = docs.flatten().to_numpy(), dists.flatten().to_numpy()
    order = np.lexsort((docs, dists, codes, owner))
    owner, codes, docs, dists = owner[order], codes[order], docs[order], dists[order]
    starts = np.flatnonzero(np.r_[True, (owner[1:] != owner[:-1]) | (codes[1:] != codes[:-1])][: len(owner)])
    ends = np.r_[starts[1:], len(owner)]
    asked: list[list[tuple[int, int, int]]] = [[] for _ in ids]  # of each query: partition, first and last mark
    for c, i, j in zip(codes[starts].tolist(), starts.tolist(), ends.tolist(), strict=True):
        asked[owner[i]].append((c, i, j))
    kinds = [tuple(c for c, _, _ in x) for x in asked]
    cut: list[list[int]] = []
    for i in sorted(range(len(ids)), key=kinds.__getitem__):
        if not cut or len(cut[-1]) == BLOCK or (kinds[cut[-1][-1]] != kinds[i] and 4 * len(cut[-1]) >= BLOCK):
            cut.append([])
        cut[-1].append(i)
    out = []
    for block in cut:
        of: dict[int, list[tuple[int, int, int]]] = {}
        for b, i in enumerate(block):
            for c, first, last in asked[i]:
                of.setdefault(c, []).append((b, first, last))
        held = {}
        for c, some in of.items():
            n = np.array([j - i for _, i, j in some])
            m, d = np.zeros((len(some), n.max()), np.int64), np.full((len(some), n.max()), np.inf)
            for row, (_, i, j) in enumerate(some):
                m[row, : j - i], d[row, : j - i] = docs[i:j], dists[i:j]
            held[names[c]] = (np.array([b for b, _, _ in some]), m, d, n)
        out.append((ids[block], q[block], held))
    return out


def _places(copies: DataFrame, marks: DataFrame) -> DataFrame:
    sent = copies.sparkSession.sparkContext.broadcast(_marked(marks.toArrow()))

    def before(d, off, own, far, bars, m):
        """How many of the marks (dists in `bars`, ids in `m`) lie before each row, or are it; d: distances by products, far(rows): the exact ones."""
        gap = bars - d[:, None]
        out, near = (gap < 0).sum(axis=1), np.flatnonzero((np.abs(gap) <= off).any(axis=1))
        d6 = np.round(far(near), 6)[:, None]
        out[near] = ((bars[near] < d6) | ((bars[near] == d6) & (m[near] <= own[near][:, None]))).sum(axis=1)
        return out

    def run(batches):
        asks = []  # of each block: squared norms, farthest mark of each query, and by partition the row of each query's marks and how many rows lie between two of them
        for _, q, held in sent.value:
            far, rows = np.full(len(q), -np.inf), {}
            for part, (at, m, d, n) in held.items():
                far[at] = np.maximum(far[at], d[np.arange(len(at)), n - 1])
                row = np.full(len(q), -1)
                row[at] = np.arange(len(at))
                rows[part] = row, np.zeros((len(at), m.shape[1] + 1), np.int64)
            asks.append(((q * q).sum(axis=1), far, rows))
        for table in chunks(batches):
            codes, names, ids, x, norms = opened(table)
            times: dict[str, np.ndarray] = {}  # by partition: how often a row of each key lies in it
            for c, name in enumerate(names):
                for part in name.split("\n"):
                    times.setdefault(part, np.zeros(len(names), np.int64))[c] += 1
            whole, apart = {}, spread(x, norms)
            for (_, q, held), (q2, most, rows) in zip(sent.value, asks, strict=True):
                here = [part for part in held if part in times]
                seen = np.any([times[part] > 0 for part in here], axis=0)[codes] if here else np.zeros(len(ids), bool)
                if not seen.any():
                    continue
                kind = kind_for(q, norms, apart)
                if kind not in whole:
                    whole[kind] = turned(x, norms, kind)
                # Rows that no query of the block asks for are left out where that saves more than it costs.
                at = np.flatnonzero(seen) if 4 * np.count_nonzero(seen) < 3 * len(seen) else None
                cols = whole[kind] if at is None else whole[kind][:, at]
                off = NEAR + error(q, norms, kind)
                line, ask = np.nextafter((most - q2 + off).astype(kind), kind(np.inf))[:, None], asking(q, kind)
                for lo in range(0, cols.shape[1], WIDE):
                    i, r, d = within(ask, cols[:, lo : lo + WIDE], line)
                    if not len(i):
                        continue
                    d, r = d + q2[i], r + lo if at is None else at[r + lo]
                    known = np.full(len(i), np.nan)  # exact distances, as they are asked for

                    def far_of(rows, known=known, i=i, r=r):
                        new = rows[np.isnan(known[rows])]
                        known[new] = exact(q, x, i[new], r[new])
                        return known[rows]

                    for part in here:
                        (_, m, bars, _), (row, n) = held[part], rows[part]
                        often = times[part][codes[r]]
                        mine = np.flatnonzero((row[i] >= 0) & (often > 0))
                        step = max(1, MARKED // bars.shape[1])
                        for some in (mine[a : a + step] for a in range(0, len(mine), step)):
                            t = row[i[some]]
                            place = before(d[some], off, ids[r[some]], lambda near, some=some: far_of(some[near]), bars[t], m[t])
                            n += np.bincount(t * n.shape[1] + place, often[some], n.size).astype(np.int64).reshape(n.shape)
        for (ids, _, held), (_, _, rows) in zip(sent.value, asks, strict=True):
            for part, (at, m, _, n) in held.items():
                i, t = np.nonzero(np.arange(m.shape[1]) < n[:, None])
                total = rows[part][1].cumsum(axis=1)[i, t]
                yield pa.RecordBatch.from_arrays([pa.array(ids[at[i]], pa.int64()), pa.array([part] * len(i), pa.string()), pa.array(m[i, t], pa.int64()), pa.array(total, pa.int64())], names=["query_id", "part", "doc_id", "n"])

    return copies.mapInArrow(run, "query_id bigint, part string, doc_id bigint, n bigint")


def secure_search(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, ef: int | None = None, k: int = 10) -> DataFrame:
    """`search.secure_search` by squared distance, at a cost that does not grow with the depth.

    The k nearest permitted rows of each routed partition, less those that are not
    among its ef nearest rows of all, permitted or not: the same as to take ef and to filter.
    Without a depth, more queries than rows are answered where they lie (`many_queries`).
    """
    if ef is None and (n := queries.count()) > max(se.MAX_BROADCAST_QUERIES, n_rows := part.part_doc.count()):
        return many_queries(queries, vectors, p, part, k, n, n_rows)
    asked = se.routed_queries(queries, p, part).withColumn("k", F.lit(k))
    classes = doc_classes(p).select("doc_id", "cls")
    key = F.concat_ws("/", "part", "cls").alias("key")
    copies = part.part_doc.join(classes, "doc_id").join(vectors.select("doc_id", "embedding"), "doc_id").select(key, "doc_id", "embedding")
    found = se.ranked(scan(dealt(copies, part.part_doc.count()), asked), k, ("query_id", "part")).select("query_id", "rs", "part", "doc_id", "dist")
    if ef is not None:
        found = found.cache()
        marks = found.select("query_id", "part", "doc_id", F.round("dist", 6).alias("dist")).join(queries.select("query_id", "qvec"), "query_id")
        found = found.join(places(vectors, part, marks).filter(F.col("place") <= ef), ["query_id", "part", "doc_id"], "left_semi")
    return se.merge(found, k)


def many_queries(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, k: int, n_queries: int, n_rows: int) -> DataFrame:
    """`secure_search` without a depth, for queries that outnumber rows: blocks of rows go to every task, and each query meets its role set's rows of the routed partitions there."""
    spark = queries.sparkSession
    homes = part.part_doc.groupBy("doc_id").agg(F.array_join(F.array_sort(F.collect_set("part")), "\n").alias("parts"))
    rows = homes.join(doc_classes(p).select("doc_id", "cls"), "doc_id").join(vectors.select("doc_id", "embedding"), "doc_id")
    rows = rows.select(F.concat_ws("/", "parts", "cls").alias("key"), "doc_id", "embedding")
    routes = part.route.groupBy("rs").agg(F.array_join(F.array_sort(F.collect_set("part")), "\n").alias("parts"))
    asked = queries.join(se.query_role_sets(queries, p), "user_id").join(routes, "rs").select(F.concat_ws("/", "parts", "rs").alias("key"), F.col("query_id").alias("doc_id"), F.col("qvec").alias("embedding"))
    n_tasks = max(spark.sparkContext.defaultParallelism, -(-n_queries // TASK_ROWS))
    asked = asked.repartition(n_tasks, "doc_id").sortWithinPartitions("key")  # queries of one role set are asked together
    n = -(-n_rows // SENT)
    n = 2 * n if n > 1 else 1  # room for uneven blocks
    found = None
    for i in range(n):
        one = _many(rows if n == 1 else rows.filter(F.pmod(F.xxhash64(F.lit(47), "doc_id"), F.lit(n)) == i), asked, k)
        found = one if found is None else found.unionByName(one)
    if n > 1:
        found = se.ranked(found.drop("rank"), k)
    return found.select("query_id", "rank", "doc_id", F.round("dist", 6).alias("dist"))


def _many(rows: DataFrame, asked: DataFrame, k: int) -> DataFrame:
    got = rows.toArrow()
    keys = got.column(0).combine_chunks().dictionary_encode() if got.num_rows else pa.array([], pa.string()).dictionary_encode()
    flat = got.column(2).combine_chunks().flatten().to_numpy(zero_copy_only=False)
    held = (keys.indices.to_numpy(), keys.dictionary.to_pylist(), got.column(1).to_numpy(), flat.reshape(len(keys), -1) if len(keys) else np.zeros((0, 1)))
    sent = rows.sparkSession.sparkContext.broadcast(held)

    def shown(row: str, ask: str) -> bool:
        (parts, cls), (routed, rs) = row.rsplit("/", 1), ask.rsplit("/", 1)
        return not set(parts.split("\n")).isdisjoint(routed.split("\n")) and not set(cls.split(",")).isdisjoint(rs.split(","))

    def run(batches):
        codes, names, docs, x = sent.value
        at, last = None, None
        for table in chunks(batches):
            asks, kinds, ids, q, _ = opened(table)
            for g, kind in enumerate(kinds):
                if kind != last:
                    at, last = np.flatnonzero(np.array([shown(name, kind) for name in names] or [False])[codes]), kind
                    mine, own = x[at].astype(np.float64), docs[at]
                    turned = np.hstack((-2 * mine, (mine * mine).sum(axis=1)[:, None])).T  # whose products are distances less the query's norm
                mine_q = np.flatnonzero(asks == g)
                for b in range(0, len(mine_q) if len(at) else 0, BLOCK):
                    n = mine_q[b : b + BLOCK]
                    some = q[n]
                    d = np.hstack((some, np.ones((len(n), 1)))) @ turned
                    near = np.arange(d.size) if len(at) <= k else np.flatnonzero(d <= (least(d, k) + 2 * NEAR)[:, None])
                    i, r = np.divmod(near, len(at))
                    far = exact(some, mine, i, r)
                    order = np.lexsort((own[r], np.round(far, 6), i))
                    i, r, far = i[order], r[order], far[order]
                    place = np.arange(len(i)) - np.searchsorted(i, i)
                    i, r, far, place = (y[place < k] for y in (i, r, far, place))
                    yield pa.RecordBatch.from_arrays([pa.array(ids[n[i]]), pa.array(place + 1), pa.array(own[r]), pa.array(far)], names=["query_id", "rank", "doc_id", "dist"])

    return asked.mapInArrow(run, "query_id bigint, rank bigint, doc_id bigint, dist double")


def true_places(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, truth: DataFrame) -> DataFrame:
    """query_id, doc_id, place of every true neighbour: its best place in a routed partition, null where none holds it."""
    best = _marked_places(queries, vectors, p, part, truth).groupBy("query_id", "doc_id").agg(F.min("place").alias("place"))
    return truth.select("query_id", "doc_id").join(best, ["query_id", "doc_id"], "left")


def _marked_places(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, truth: DataFrame) -> DataFrame:
    """query_id, part, doc_id, place of true neighbours in each routed partition that holds them."""
    routed = se.routed_queries(queries, p, part).select("query_id", "part", "qvec")
    return places(vectors, part, truth.select("query_id", "doc_id", "dist").join(routed, "query_id").join(part.part_doc, ["part", "doc_id"], "left_semi"))


def true_places_in_each(queries: DataFrame, vectors: DataFrame, p: Policy, several: list[Partitioning], truth: DataFrame) -> DataFrame:
    """which, query_id, doc_id, place: `true_places` of the first, the second, ... partitioning, numbered from 0. One scan serves them all."""
    both, named = None, F.concat_ws("/", "which", "part").alias("part")
    for i, x in enumerate(several):
        one = [df.withColumn("which", F.lit(str(i))) for df in (x.part_doc, x.route)]
        one = one[0].select(named, "doc_id"), one[1].select("rs", named)
        both = one if both is None else [a.unionByName(b) for a, b in zip(both, one, strict=True)]
    which = F.substring_index("part", "/", 1).cast("int").alias("which")
    best = _marked_places(queries, vectors, p, Partitioning("each", *both), truth).groupBy(which, "query_id", "doc_id").agg(F.min("place").alias("place"))
    wanted = truth.select(F.explode(F.array(*(F.lit(i) for i in range(len(several))))).alias("which"), "query_id", "doc_id")
    return wanted.join(best, ["which", "query_id", "doc_id"], "left")


def recalls(placed: DataFrame, efs: list[int]) -> DataFrame:
    """ef, recall from places of true neighbours."""
    return se.mean_recalls(placed, efs)


def recall_by_depth(queries: DataFrame, vectors: DataFrame, p: Policy, part: Partitioning, truth: DataFrame, efs: list[int]) -> DataFrame:
    """`search.recall_by_depth` without candidate lists: only the places of true neighbours are counted."""
    return recalls(true_places(queries, vectors, p, part, truth), efs)
