"""Documents linked by the Jaccard similarity of their word shingles, and their components.

Only what can link is moved. Equal shingle sets are one class with one
representative. Hashes of shingles meet in shards, a batch's own repeats already
taken out, and only shingles of two or more classes come back to their class;
a class of which fewer than 75 of 100 shingles come back links with nothing.
Of the rest, shingles are ordered by frequency, and each class has a short
prefix of its rarest ones; two classes that link share one of the prefix.

A first round groups classes by min-hashes and links what it finds; groups whose
classes are one component already need no further look, so large groups of
copies never grow into pairs. A second round takes, for every two components
that meet in a prefix shingle, the classes that meet there, in blocks. Within a
group or a pair of blocks, partners are found by T-occurrence search: the short
inverted lists are merged by a heap, the long ones probed by binary search.

A shingle is held by a 64-bit hash. A class is one of 128 bits, of which the
search for candidates uses 64.

Defined results: a document without words has 0 shingles and is its own
component; rows that share an id are one node; rows with a null id link like
others and get the smallest id of their component, null if there is none; equal
similarity is no tie, as every link counts. Where one document of each group
stays, it is that of the smallest id (a null id counts as the largest), of equal
ids any one; rows without words all stay. Extra columns are left alone.
"""

from __future__ import annotations

import hashlib
import heapq
from bisect import bisect_left

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.llm.common import chunks, id_and_bytes, per_text, stored, table

WORDS, ABOVE, OF = 5, 75, 100
#: Shingles of a shard; classes of a group and at most of a block; min-hashes of the first round.
SHARD, GROUP, BLOCK, DRAWS = 1_500_000, 96, 256, 2
#: Bytes of text whose repeats are taken out before the shuffle.
RUN = 8 << 20
#: Divides the required overlap in the choice of the number of long lists.
LONG_SHARE = 0.03
LAST = (1 << 63) - 1
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def byte_values() -> np.ndarray:
    """An odd 64-bit value for each byte."""
    x = np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xAEF17502108EF2D9)
    return (x ^ (x >> np.uint64(29))) | np.uint64(1)


def stir(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(texts: list[bytes]) -> list[np.ndarray]:
    """The sorted hashes of each text's distinct shingles."""
    buf = np.frombuffer(b" ".join(texts).lower() + b" ", np.uint8)
    space = np.zeros(256, bool)
    space[[32, 9, 10, 11, 12, 13]] = True
    blank = space[buf]
    head = ~blank
    head[1:] &= blank[:-1]
    starts = np.flatnonzero(head)
    if not len(starts):
        return [np.zeros(0, np.uint64)] * len(texts)
    place = np.arange(len(buf)) - np.repeat(starts, np.diff(np.concatenate((starts, [len(buf)])))) if starts[0] == 0 else np.concatenate((np.zeros(starts[0], np.int64), np.arange(starts[0], len(buf)) - np.repeat(starts, np.diff(np.concatenate((starts, [len(buf)]))))))
    value = byte_values()[buf] * stir((place + 1).astype(np.uint64) * MULTIPLIER)
    value[blank] = 0
    word = stir(np.add.reduceat(stir(value) * ~blank, starts))
    begins = np.concatenate(([0], np.cumsum([len(t) + 1 for t in texts])))
    first = np.searchsorted(starts, begins)
    n = len(word) - WORDS + 1
    h = np.full(max(n, 0), 7, np.uint64)
    for k in range(WORDS if n > 0 else 0):
        h = stir((h + word[k : k + n]) * MULTIPLIER)
    out = []
    for a, b in zip(first.tolist(), first[1:].tolist(), strict=False):
        if b - a >= WORDS:
            out.append(np.unique(h[a : b - WORDS + 1]))
        elif b > a:
            x = np.array([b - a], np.uint64)
            for w in word[a:b]:
                x = stir((x + w) * MULTIPLIER)
            out.append(x)
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def digest(hashes: np.ndarray) -> tuple[int, int]:
    """128 bits of a set, as two signed numbers."""
    a, b = np.frombuffer(hashlib.blake2b(hashes.tobytes(), digest_size=16).digest(), np.int64)
    return int(a), int(b)


def spans(sorted_keys: np.ndarray) -> list[tuple[int, int, int]]:
    """Each key that occurs, with the begin and end of its rows: work by what is there, however many keys there might be."""
    if not len(sorted_keys):
        return []
    begin = np.flatnonzero(np.concatenate(([True], sorted_keys[1:] != sorted_keys[:-1])))
    return list(zip(sorted_keys[begin].tolist(), begin.tolist(), [*begin[1:].tolist(), len(sorted_keys)], strict=True))


def set_rows(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, the columns `more`, n, d1, d2: the size and digest of each document's shingle set."""

    def work(texts):
        found = [(len(s), *digest(s)) for i in range(0, len(texts), 100) for s in shingles(texts[i : i + 100])]
        return {"n": [x[0] for x in found], "d1": [x[1] for x in found], "d2": [x[2] for x in found]}

    return per_text(id_and_bytes(docs, *more), "n long, d1 long, d2 long", lambda: work)


def entry_rows(docs: DataFrame, n_shards: int) -> DataFrame:
    """shard, settled, hashes, classes: a batch's shingles by shard, each with the class that holds it.

    A shingle that two classes of the batch hold is settled: it goes back to all
    of them, and one entry without a class tells the shard that it is there.
    """

    def run(batches):
        schema = pa.schema([("shard", pa.int64()), ("settled", pa.bool_()), ("hashes", pa.binary()), ("classes", pa.binary())])
        for texts in (t for b in batches for _, t in chunks(b, limit=RUN)):
            held: dict[int, np.ndarray] = {}
            for i in range(0, len(texts), 100):
                for s in shingles(texts[i : i + 100]):
                    if len(s):
                        held.setdefault(digest(s)[0], s)
            if not held:
                continue
            names = np.fromiter(held, np.int64, len(held))
            h = np.concatenate(list(held.values()))
            c = np.repeat(names, [len(s) for s in held.values()])
            order = np.argsort(h)
            h, c = h[order], c[order]
            new = np.concatenate(([True], h[1:] != h[:-1]))
            alone = new & np.concatenate((new[1:], [True]))
            # What is settled goes by any shard, the same for no two batches.
            spread = int(names[0] % n_shards)
            rows = []
            twice = ~alone
            if twice.any():
                hs, cs = h[twice], c[twice]
                piece = 1 << 16
                rows += [((spread + i) % n_shards, True, hs[i * piece : (i + 1) * piece], cs[i * piece : (i + 1) * piece]) for i in range(-(-len(hs) // piece))]
                lead = h[new & twice]
                shard = (lead % np.uint64(n_shards)).astype(np.int64)
                for k in np.unique(shard).tolist():
                    rows.append((k, False, lead[shard == k], np.zeros(0, np.int64)))
            h, c = h[alone], c[alone]
            shard = (h % np.uint64(n_shards)).astype(np.int64)
            order = np.lexsort((c, shard))
            shard, h, c = shard[order], h[order], c[order]
            rows += [(k, False, h[x:y], c[x:y]) for k, x, y in spans(shard)]
            for i in range(0, len(rows), 64):
                part = rows[i : i + 64]
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in part], pa.int64()), pa.array([r[1] for r in part], pa.bool_()), pa.array([r[2].tobytes() for r in part], pa.binary()), pa.array([r[3].tobytes() for r in part], pa.binary())], schema=schema)
            del rows, h, c, shard, order, held
            pa.default_memory_pool().release_unused()

    return id_and_bytes(docs).mapInArrow(run, "shard long, settled boolean, hashes binary, classes binary")


def shared_rows(entries: DataFrame, n_shards: int) -> DataFrame:
    """bucket, classes, hashes: what two or more classes hold, packed by the class's bucket."""

    def meet(key, rows):
        h, c = [], []
        settled_h, settled_c, known = [], [], []
        for s, x, y in zip(rows["settled"].to_pylist(), rows["hashes"].to_pylist(), rows["classes"].to_pylist(), strict=True):
            x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.int64)
            if s:
                settled_h.append(x)
                settled_c.append(y)
            elif len(y):
                h.append(x)
                c.append(y)
            else:
                known.append(x)
        h, c = (np.concatenate([np.zeros(0, t), *v]) for v, t in ((h, np.uint64), (c, np.int64)))
        known = np.unique(np.concatenate([np.zeros(0, np.uint64), *known]))
        order = np.argsort(h)
        h, c = h[order], c[order]
        new = np.concatenate(([True], h[1:] != h[:-1])) if len(h) else np.zeros(0, bool)
        group = np.cumsum(new) - 1
        first = c[new]
        differs = np.bincount(group, c != first[group], len(first)) > 0 if len(h) else np.zeros(0, bool)
        keep = differs[group] if len(h) else np.zeros(0, bool)
        if len(known) and len(h):
            keep |= known[np.minimum(np.searchsorted(known, h), len(known) - 1)] == h
        h, c = np.concatenate([h[keep], *settled_h]), np.concatenate([c[keep], *settled_c])
        bucket = c % n_shards
        order = np.lexsort((c, bucket))
        bucket, h, c = bucket[order], h[order], c[order]
        found = spans(bucket)
        return pa.table({"bucket": pa.array([k for k, _, _ in found], pa.int64()), "classes": pa.array([c[x:y].tobytes() for _, x, y in found], pa.binary()), "hashes": pa.array([h[x:y].tobytes() for _, x, y in found], pa.binary())})

    return entries.groupBy("shard").applyInArrow(meet, "bucket long, classes binary, hashes binary")


def candidate_sets(shared: DataFrame, classes: DataFrame, n_shards: int) -> DataFrame:
    """node, n, hashes of the classes of which enough shingles are shared to link with another."""

    def gather(key, rows, known):
        c = np.concatenate([np.zeros(0, np.int64), *(np.frombuffer(x, np.int64) for x in rows["classes"].to_pylist())])
        h = np.concatenate([np.zeros(0, np.uint64), *(np.frombuffer(x, np.uint64) for x in rows["hashes"].to_pylist())])
        order = np.lexsort((h, c))
        c, h = c[order], h[order]
        keep = np.concatenate(([True], (c[1:] != c[:-1]) | (h[1:] != h[:-1]))) if len(c) else np.zeros(0, bool)
        c, h = c[keep], h[keep]
        d1, node, n = (known[k].to_numpy() for k in ("d1", "node", "n"))
        x, y = np.searchsorted(c, d1), np.searchsorted(c, d1, side="right")
        ok = np.flatnonzero((y - x) * OF >= ABOVE * n)
        return pa.table({"node": node[ok], "n": n[ok], "hashes": pa.array([h[i:j].tobytes() for i, j in zip(x[ok].tolist(), y[ok].tolist(), strict=True)], pa.binary())})

    own = classes.withColumn("bucket", F.pmod("d1", F.lit(n_shards)))
    return shared.groupBy("bucket").cogroup(own.groupBy("bucket")).applyInArrow(gather, "node long, n long, hashes binary")


def needed(n: int, m: int) -> int:
    """The least overlap of sets of n and m elements that link."""
    return -(-ABOVE * (n + m) // (OF + ABOVE))


class Inverted:
    """Inverted lists of sets, and T-occurrence search in them."""

    def __init__(self, sets: list[np.ndarray], sizes: list[int]):
        self.sizes = sizes
        self.lists: dict[int, list[int]] = {}
        for i, s in enumerate(sets):
            for t in s.tolist():
                self.lists.setdefault(t, []).append(i)

    def search(self, query: np.ndarray, n: int, skip, found) -> None:
        """Calls `found(i)` for each set that links with `query` of full size n, unless `skip(i)` by then."""
        least = -(-ABOVE * n // OF)
        lists = sorted((x for t in query.tolist() if (x := self.lists.get(t))), key=len)
        if len(lists) < least:
            return
        longest = len(lists[-1])
        n_long = min(least - 1, int(least / (LONG_SHARE * np.log2(longest + 1) + 1)), len(lists) - 1)
        short, long_ = lists[: len(lists) - n_long], lists[len(lists) - n_long :]
        last, count = -1, 0
        for i in heapq.merge(*short):
            if i == last:
                count += 1
                continue
            if count >= least - n_long:
                self.probe(last, count, long_, n, skip, found)
            last, count = i, 1
        if count >= least - n_long:
            self.probe(last, count, long_, n, skip, found)

    def probe(self, i: int, count: int, long_: list[list[int]], n: int, skip, found) -> None:
        m = self.sizes[i]
        want = needed(n, m)
        if skip(i) or m * OF < ABOVE * n or n * OF < ABOVE * m or count + len(long_) < want:
            return
        left = len(long_)
        for x in long_:
            left -= 1
            at = bisect_left(x, i)
            if at < len(x) and x[at] == i:
                count += 1
                if count >= want:
                    break
            elif count + left < want:
                return
        if count >= want:
            found(i)


class Forest:
    """Components of a few nodes."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def top(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = i = self.up[self.up[i]]
        return i

    def unite(self, i: int, j: int) -> bool:
        i, j = self.top(i), self.top(j)
        self.up[max(i, j)] = min(i, j)
        return i != j


def arrays(rows: pa.Table) -> tuple[np.ndarray, list[int], list[np.ndarray]]:
    node = rows["node"].to_numpy()
    order = np.argsort(node, kind="stable").tolist()
    sets = rows["hashes"].to_pylist()
    n = rows["n"].to_pylist()
    return node[order], [n[i] for i in order], [np.frombuffer(sets[i], np.uint64) for i in order]


def links_within(key, rows):
    """Links that join the sets of a group into the components they form among themselves."""
    node, n, sets = arrays(rows)
    index, forest, out = Inverted(sets, n), Forest(len(n)), []
    for i in range(1, len(n)):
        index.search(sets[i], n[i], lambda j, i=i: j >= i or forest.top(i) == forest.top(j), lambda j, i=i: forest.unite(i, j) and out.append((int(node[j]), int(node[i]))))
    return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([y for _, y in out], pa.int64())})


def links_across(key, left, right):
    """Links that join the components of two blocks, or of one block if there is no other."""
    a, n_a, sets_a = arrays(left)
    b, n_b, sets_b = arrays(right) if right.num_rows else (a, n_a, sets_a)
    comp = {}
    for rows in (left, right):
        comp |= dict(zip(rows["node"].to_pylist(), rows["comp"].to_pylist(), strict=True))
    place = {c: i for i, c in enumerate(sorted(set(comp.values())))}
    forest, out, index = Forest(len(place)), [], Inverted(sets_b, n_b)
    at_b = [place[comp[x]] for x in b.tolist()]
    for i, x in enumerate(a.tolist()):
        mine = place[comp[x]]
        index.search(sets_a[i], n_a[i], lambda j, m=mine: forest.top(m) == forest.top(at_b[j]), lambda j, m=mine, x=x: forest.unite(m, at_b[j]) and out.append((x, int(b[j]))))
    return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([y for _, y in out], pa.int64())})


def grouped_links(sets: DataFrame) -> DataFrame:
    """Links found among the classes that share a min-hash, in groups of about `GROUP`."""

    def draws(batches):
        schema = pa.schema([("node", pa.int64()), ("draw", pa.int32()), ("low", pa.int64())])
        for b in batches:
            nodes = b.column(b.schema.get_field_index("node")).to_pylist()
            rows = []
            for node, s in zip(nodes, b.column(b.schema.get_field_index("hashes")).to_pylist(), strict=True):
                h = np.frombuffer(s, np.uint64)
                rows += [(node, k, int(stir(h ^ np.uint64(0xA24BAED4963EE407 * (k + 1) & 0xFFFFFFFFFFFFFFFF)).min().view(np.int64))) for k in range(DRAWS)]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], schema.field(k).type) for k in range(3)], schema=schema)

    keys = stored(sets.mapInArrow(draws, "node long, draw int, low long"))
    parts = keys.groupBy("draw", "low").agg(F.count("*").alias("members")).filter("members > 1").select("draw", "low", F.ceil(F.col("members") / GROUP).cast("int").alias("parts"))
    member = keys.join(stored(parts), ["draw", "low"]).withColumn("part", F.pmod(F.xxhash64("draw", "node"), "parts").cast("int")).drop("parts")
    return member.join(sets, "node").groupBy("draw", "low", "part").applyInArrow(links_within, "a long, b long")


def prefixes(sets: DataFrame) -> DataFrame:
    """node, token: the rarest shared shingles of each class, as many as a link must touch."""

    def rows(batches):
        schema = pa.schema([("node", pa.int64()), ("token", pa.int64()), ("size", pa.int64())])
        for b in batches:
            node = b.column(b.schema.get_field_index("node")).to_numpy()
            n = b.column(b.schema.get_field_index("n")).to_pylist()
            held = [np.frombuffer(x, np.int64) for x in b.column(b.schema.get_field_index("hashes")).to_pylist()]
            size = np.array([len(h) - -(-ABOVE * m // OF) + 1 for h, m in zip(held, n, strict=True)], np.int64)
            for i in range(0, len(held), 200):
                part = held[i : i + 200]
                many = [len(h) for h in part]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(node[i : i + 200], many)), pa.array(np.concatenate([np.zeros(0, np.int64), *part])), pa.array(np.repeat(size[i : i + 200], many))], schema=schema)

    tokens = sets.mapInArrow(rows, "node long, token long, size long")
    often = stored(tokens.groupBy("token").agg(F.count("*").alias("often")))

    ranked = tokens.join(often, "token").filter("size > 0").groupBy("node", "size").agg(F.array_sort(F.collect_list(F.struct("often", "token"))).alias("all"))
    first = ranked.select("node", F.explode(F.slice("all", F.lit(1), F.col("size").cast("int"))).alias("x"))
    return first.filter("x.often > 1").select("node", F.col("x.token").alias("token"))


def crossing_links(prefix: DataFrame, sets: DataFrame, component: DataFrame) -> DataFrame:
    """Links that join components that meet in a prefix shingle: block by block of classes, never pair by pair.

    Classes that meet others are put into blocks by the least of the shingles in
    which they or those they meet do, so that those that are alike lie together.
    Two blocks are searched against each other once, if they share such a shingle.
    """
    rows = prefix.join(component, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    mixed = stored(rows.groupBy("token").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).filter("x < y").select("token"))
    rows = stored(rows.join(mixed, "token"))
    nodes = rows.groupBy("node", "comp").agg(F.min("token").alias("lead"))
    near = rows.select("token", "node").join(nodes.select("node", "lead"), "node")
    # Written out, so that the join below has two shuffles and a hot shingle's rows can be dealt to several tasks.
    least = stored(near.groupBy("token").agg(F.min("lead").alias("lead")))
    nodes = rows.join(least, "token").groupBy("node", "comp").agg(F.min("lead").alias("lead"))
    parts = nodes.groupBy("lead").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("parts"))
    nodes = nodes.join(parts, "lead").select("node", "comp", F.xxhash64("lead", F.pmod(F.xxhash64("node"), "parts")).alias("block"))
    nodes = stored(nodes)
    meets = stored(rows.select("token", "node").join(nodes.select("node", "block"), "node").groupBy("token", "block").agg(F.min("node").alias("least"), F.max("node").alias("most")))
    pairs = meets.select("token", F.col("block").alias("a_block")).join(meets.select("token", F.col("block").alias("b_block")), "token").filter("a_block < b_block").select("a_block", "b_block").distinct()
    alone = meets.filter("least < most").select(F.col("block").alias("a_block"), F.col("block").alias("b_block")).distinct()
    pairs = stored(pairs.union(alone))
    held = nodes.join(sets, "node")
    sides = []
    for mine in ("a_block", "b_block"):
        own = pairs.filter("a_block < b_block") if mine == "b_block" else pairs
        own = own.join(held.withColumnRenamed("block", mine), mine)
        sides.append(own.select(*(F.col(c).alias(c) for c in ("a_block", "b_block", "node", "comp", "n", "hashes"))).groupBy("a_block", "b_block"))
    return sides[0].cogroup(sides[1]).applyInArrow(links_across, "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """node, comp: the smallest node that each linked node reaches, by large and small stars in turn."""
    edges = stored(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct())
    state = None
    while True:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(low, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        edges = stored(small.filter("u <> v").distinct())
        got = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if got == state:
            return edges.groupBy("u").agg(F.min("v").alias("comp")).withColumnRenamed("u", "node")
        state = got


def labelled(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, the columns `more`, n, node and comp of every document: its class and the smallest class reached; null without words.

    A class is named by its smallest id, one without ids by a number above all ids.
    """
    sets = stored(set_rows(docs, *more))
    classes = sets.filter("n > 0").groupBy("d1", "d2", "n").agg(F.min("doc_id").alias("low"))
    top = sets.agg(F.max("doc_id")).first()[0]
    above = F.lit(max(top, 0) + 1 if top is not None else 1)
    classes = stored(classes.select("d1", "d2", "n", F.coalesce("low", above + F.pmod("d1", F.lit(LAST) - above)).alias("node")))
    total = classes.agg(F.sum("n")).first()[0] or 0
    n_shards = max(64, -(-total // SHARD))
    shared = shared_rows(entry_rows(docs, n_shards), n_shards)
    found = stored(candidate_sets(shared, classes, n_shards))
    links = stored(grouped_links(found))
    # An id that stands in several classes is one node: its classes are linked.
    ids = sets.filter("n > 0 and doc_id is not null").join(classes, ["d1", "d2", "n"]).select(F.col("doc_id").alias("a"), F.col("node").alias("b"))
    several = stored(ids.join(ids.groupBy("a").agg(F.min("b").alias("x"), F.max("b").alias("y")).filter("x < y").select("a"), "a", "left_semi"))
    component = stored(components(links.union(several)))
    links = links.union(several).union(stored(crossing_links(prefixes(found), found, component)))
    component = stored(components(links))
    named = classes.join(component, "node", "left").select("d1", "d2", "n", F.coalesce("comp", "node").alias("comp"))
    # A number above all ids stands for none.
    return sets.join(named, ["d1", "d2", "n"], "left").select("doc_id", *more, "n", "comp", F.when(F.col("comp") < above, F.col("comp")).alias("low"))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles and component_id of every document."""
    return labelled(docs).select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("low")).otherwise(F.col("doc_id")).alias("component_id"))


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of `docs` for each component, and all rows without words."""
    text = F.xxhash64(F.coalesce("text", F.lit("")))
    rows = labelled(docs.select("doc_id", "text", text.alias("text_hash")), "text_hash")
    best = rows.filter("n > 0").groupBy("comp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_hash")).alias("x"))
    best = stored(best.select("comp", F.col("x.doc_id").alias("id"), F.col("x.text_hash").alias("hash")))
    same = F.col("doc_id").eqNullSafe(F.col("id")) & (F.col("text_hash") == F.col("hash"))
    times = rows.filter("n > 0").join(best.drop("comp"), same).groupBy("id", "hash").agg(F.count("*").alias("times"))
    empty = rows.filter("n = 0").select(F.col("doc_id").alias("id"), F.col("text_hash").alias("hash")).distinct().withColumn("times", F.lit(1))
    kept = stored(times.unionByName(empty))
    own = docs.withColumn("own_hash", text).alias("d")
    with_id = lambda k: own.join(k, F.col("d.doc_id").eqNullSafe(F.col("id")) & (F.col("d.own_hash") == F.col("hash")), "left_semi")
    # Repeated rows of one id and text are few: only they are dealt by id once more.
    once, often = with_id(kept.filter("times = 1")), with_id(kept.filter("times > 1"))
    return once.unionByName(often.dropDuplicates(["doc_id", "own_hash"])).select(*(F.col(f"`{c}`") for c in docs.columns))


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The component of every whole document among near duplicates."""
    return near_duplicates(table(spark, sf_dir, "documents"))


ORACLE = r"""
WITH RECURSIVE words AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), shingles AS (
    SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
        ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i : i + 4], ' ')) END) AS s FROM words
), sizes AS (
    SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id
), common AS (
    SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM shingles a JOIN shingles b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL
), links AS (
    SELECT x, y FROM common JOIN sizes p ON p.doc_id = x JOIN sizes q ON q.doc_id = y WHERE 100 * c >= 75 * (p.n + q.n - c)
), reach AS (
    SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT reach.x, links.y FROM reach JOIN links ON links.x = reach.y
)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, m AS component_id
FROM (SELECT x AS doc_id, min(y) AS m FROM reach GROUP BY x) d LEFT JOIN sizes USING (doc_id)
"""
