"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

Text becomes an array of code points, each code point one of a few classes.
A small automaton tells where pieces begin. Its transition functions form a
finite monoid; a prefix scan over ids of monoid elements gives the state at
every character without a regular expression and without a loop over
characters. The slices go to a cache of merged pieces; pieces not yet in it are
merged together, many at a time, in arrays.

The pieces are those of the pattern
``'(s|t|re|ve|m|ll|d) | ?letters+ | ?numbers+ | ?others+ | space+(?!nonspace) | space+``.

Defined results: a null text is the empty text; an empty text has no ids and
decodes to no bytes; repeated rows give repeated rows; extra columns are left
alone by `encode` and `decode`.
"""

from __future__ import annotations

import base64
import hashlib
import unicodedata
from collections.abc import Iterable

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from aclvec.llm.common import id_and_bytes, per_text, table

# The code points of White_Space.
WHITE_SPACE = [9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]

#: Classes of a character, after a look at its neighbours to the right.
LETTER, NUMBER, OTHER, BLANK_IN, BLANK_LAST, SPACE_LAST, TICK2, TICK3 = range(8)
#: States: what the last character belongs to. FRESH: nothing, the next one begins a piece.
FRESH, IN_L, IN_N, IN_O, IN_B, LONE_SPACE, EXPECT1, EXPECT2 = range(8)


def transitions() -> tuple[np.ndarray, np.ndarray]:
    """next_state[class, state] and begins[class, state] of the automaton."""
    step = np.zeros((8, 8), np.uint8)
    begins = np.ones((8, 8), bool)
    home = {LETTER: IN_L, NUMBER: IN_N, OTHER: IN_O}
    for c in range(8):
        for s in range(8):
            if s == EXPECT2:
                step[c, s], begins[c, s] = EXPECT1, False
            elif s == EXPECT1:
                step[c, s], begins[c, s] = FRESH, False
            elif c in home:
                step[c, s], begins[c, s] = home[c], s not in (home[c], LONE_SPACE)
            elif c in (TICK2, TICK3):
                # An apostrophe within others, or behind the space that it takes along, is one of the others.
                own = s in (IN_O, LONE_SPACE)
                step[c, s] = IN_O if own else EXPECT1 if c == TICK2 else EXPECT2
                begins[c, s] = not own
            elif c == BLANK_IN:
                step[c, s], begins[c, s] = IN_B, s != IN_B
            else:  # the last blank before something else: a space goes with what follows
                step[c, s] = LONE_SPACE if c == SPACE_LAST else FRESH
    return step, begins


class PieceFinder:
    """Finds where the pieces of texts begin."""

    def __init__(self, width: int = 64):
        self.width = width
        kind = np.full(0x110000, OTHER, np.uint8)
        category = np.fromiter((ord(unicodedata.category(chr(c))[0]) for c in range(0x110000)), np.uint8, 0x110000)
        kind[category == ord("L")] = LETTER
        kind[category == ord("N")] = NUMBER
        kind[WHITE_SPACE] = BLANK_IN
        self.kind = kind
        step, self.begins = transitions()
        elements: dict[bytes, int] = {bytes(range(8)): 0}
        todo = [bytes(range(8))]
        gens = [step[c].tobytes() for c in range(8)]
        while todo:  # closure of the transition functions under composition
            f = todo.pop()
            for g in gens:
                h = bytes(g[x] for x in f)
                if h not in elements:
                    elements[h] = len(elements)
                    todo.append(h)
        funcs = np.array([list(f) for f in elements], np.uint8)
        n = len(funcs)
        kind_of = np.uint8 if n <= 256 else np.uint16
        index = {f.tobytes(): i for i, f in enumerate(funcs)}
        self.product = np.array([[index[funcs[b][funcs[a]].tobytes()] for b in range(n)] for a in range(n)], kind_of)
        self.generator = np.array([index[g] for g in gens], kind_of)
        self.funcs, self.n = funcs, n

    def classes(self, points: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """The class of each code point; `ends`: positions of the last one of each text."""
        k = self.kind[points]
        blank = k == BLANK_IN
        follows = np.empty(len(k), bool)  # something that is no blank follows in the same text
        follows[:-1] = ~blank[1:]
        follows[ends] = False
        last = blank & follows
        k[last] = np.where(points[last] == 32, SPACE_LAST, BLANK_LAST)
        ticks = np.flatnonzero(points == 39)
        if len(ticks):
            text_end = ends[np.searchsorted(ends, ticks)]
            padded = np.concatenate((points, [0, 0]))
            a = np.where(ticks + 1 <= text_end, padded[ticks + 1], 0)
            b = np.where(ticks + 2 <= text_end, padded[ticks + 2], 0)
            two = np.isin(a, [ord(c) for c in "stmd"])
            three = (a == ord("r")) & (b == ord("e")) | (a == ord("v")) & (b == ord("e")) | (a == ord("l")) & (b == ord("l"))
            k[ticks[two]], k[ticks[three]] = TICK2, TICK3
        return k

    def starts(self, points: np.ndarray, text_starts: np.ndarray, text_ends: np.ndarray) -> np.ndarray:
        """Flags of the code points at which a piece begins. Texts lie one after the other, none is empty."""
        k = self.classes(points, text_ends)
        w = self.width
        rows = -(-len(k) // w)
        gen = np.zeros(rows * w, self.product.dtype)
        gen[: len(k)] = self.generator[k]
        # A text begins anew: its first element is the constant function of what FRESH becomes.
        reset = np.array([self._constant(self.funcs[g][FRESH]) for g in self.generator], self.product.dtype)
        gen[text_starts] = reset[k[text_starts]]
        grid = np.ascontiguousarray(gen.reshape(rows, w).T)
        flat, n = self.product.ravel(), self.n
        for j in range(1, w):
            grid[j] = flat[grid[j - 1].astype(np.int32) * n + grid[j]]
        total, jump = grid[-1].copy(), 1
        while jump < rows:  # the associative scan over the rows' functions
            total[jump:] = flat[total[:-jump].astype(np.int32) * n + total[jump:]]
            jump *= 2
        entry = np.full(rows, FRESH, np.uint8)
        entry[1:] = self.funcs[total[:-1], FRESH]
        after = self.funcs.ravel()[grid.astype(np.int32) * 8 + entry].T.ravel()[: len(k)]
        before = np.empty(len(k), np.uint8)
        before[1:] = after[:-1]
        before[text_starts] = FRESH
        return self.begins.ravel()[k.astype(np.int32) * 8 + before]

    def _constant(self, state: int) -> int:
        if not hasattr(self, "_const"):
            self._const = {}
        if state not in self._const:
            f = np.full(8, state, np.uint8)
            hit = np.flatnonzero((self.funcs == f).all(axis=1))
            if not len(hit):  # add the constant to the monoid: composing with it is plain
                self.funcs = np.vstack([self.funcs, f])
                m = len(self.funcs)
                index = {g.tobytes(): i for i, g in enumerate(self.funcs)}
                todo = list(index)
                while todo:
                    g = todo.pop()
                    for h in list(index):
                        for c in (bytes(h[x] for x in g), bytes(g[x] for x in h)):
                            if c not in index:
                                index[c] = m
                                m += 1
                                todo.append(c)
                self.funcs = np.array([list(g) for g in index], np.uint8)
                self.n = m
                dtype = np.uint8 if m <= 256 else np.uint16
                self.product = np.array([[index[self.funcs[b][self.funcs[a]].tobytes()] for b in range(m)] for a in range(m)], dtype)
                self.generator = self.generator.astype(dtype)
                return self._constant(state)
            self._const[state] = int(hit[0])
        return self._const[state]


class Encoder:
    """Ranks, cached pieces and merges. `ranks`: bytes of a token to its id."""

    def __init__(self, ranks: dict[bytes, int], cache_size: int = 400_000, widest: int = 48):
        self.ranks, self.cache_size, self.widest = ranks, cache_size, widest
        self.finder = PieceFinder()
        self.seed = {t: i.to_bytes(4, "little") for t, i in ranks.items()}
        self.cache = dict(self.seed)
        self.byte_ids = np.array([ranks[bytes([b])] for b in range(256)], np.int64)
        pairs = {(ranks[t[:i]] << 32) | ranks[t[i:]]: r for t, r in ranks.items() for i in range(1, len(t)) if t[:i] in ranks and t[i:] in ranks}
        size = 1 << max(4, (len(pairs) * 4).bit_length())
        self.mask, self.none = size - 1, np.iinfo(np.int64).max
        self.keys, self.vals = np.full(size, -1, np.int64), np.full(size, self.none, np.int64)
        at = self._slot(np.array(list(pairs), np.int64))
        for key, val, i in zip(pairs, pairs.values(), at.tolist(), strict=True):
            while self.keys[i] != -1:
                i = (i + 1) & self.mask
            self.keys[i], self.vals[i] = key, val

    def _slot(self, key: np.ndarray) -> np.ndarray:
        h = key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return ((h >> np.uint64(29)) & np.uint64(self.mask)).astype(np.int64)

    def pair_ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The rank of each pair's union; a large number if it is no token."""
        key = (left << 32) | right
        at = self._slot(key)
        found = self.keys[at]
        out = np.where(found == key, self.vals[at], self.none)
        open_ = np.flatnonzero((found != key) & (found != -1))
        while len(open_):
            at[open_] = (at[open_] + 1) & self.mask
            found = self.keys[at[open_]]
            hit = found == key[open_]
            out[open_[hit]] = self.vals[at[open_[hit]]]
            open_ = open_[~hit & (found != -1)]
        return out

    def merge_long(self, piece: bytes) -> bytes:
        """A piece too long for the arrays of `merge_many`, by a heap over its pairs."""
        import heapq

        ids: list = [int(self.byte_ids[b]) for b in piece]
        n = len(ids)
        nxt, prv = [*range(1, n), -1], [-1, *range(n - 1)]
        arr = np.array(ids, np.int64)
        heap = [(r, i, ids[i], ids[i + 1]) for i, r in enumerate(self.pair_ranks(arr[:-1], arr[1:]).tolist()) if r != self.none]
        heapq.heapify(heap)
        rank = lambda a, b: int(self.pair_ranks(np.array([a], np.int64), np.array([b], np.int64))[0])
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = nxt[i] if ids[i] is not None else -1
            if j < 0 or ids[i] != a or ids[j] != b:
                continue
            ids[i], ids[j] = r, None
            nxt[i] = nxt[j]
            if nxt[j] >= 0:
                prv[nxt[j]] = i
            for x, y in ((prv[i], i), (i, nxt[i])):
                if x >= 0 and y >= 0 and (q := rank(ids[x], ids[y])) != self.none:
                    heapq.heappush(heap, (q, x, ids[x], ids[y]))
        return np.array([x for x in ids if x is not None], "<u4").tobytes()

    def merge_many(self, pieces: list[bytes]) -> dict[bytes, bytes]:
        """The ids of many pieces, as little-endian 32-bit numbers."""
        out = {p: self.merge_long(p) for p in pieces if len(p) > self.widest}
        by_size: dict[int, list[bytes]] = {}
        for p in pieces:
            if len(p) <= self.widest:
                by_size.setdefault(len(p), []).append(p)
        for size, group in by_size.items():
            ids = self.byte_ids[np.frombuffer(b"".join(group), np.uint8).reshape(len(group), size)]
            rank = self.pair_ranks(ids[:, :-1].ravel(), ids[:, 1:].ravel()).reshape(len(group), size - 1)
            who = np.arange(len(group))
            while len(who):
                best = rank.argmin(axis=1) if rank.shape[1] else np.zeros(len(who), np.int64)
                row = np.arange(len(who))
                low = rank[row, best] if rank.shape[1] else np.full(len(who), self.none)
                done = low == self.none
                if done.any():
                    flat, w = ids[done].astype("<u4").tobytes(), 4 * ids.shape[1]
                    for n, i in enumerate(who[done].tolist()):
                        out[group[i]] = flat[n * w : (n + 1) * w]
                    go = ~done
                    who, ids, rank, best, low = who[go], ids[go], rank[go], best[go], low[go]
                    row = np.arange(len(who))
                    if not len(who):
                        break
                ids[row, best] = low
                keep = np.ones(ids.shape, bool)
                keep[row, best + 1] = False
                width = ids.shape[1] - 1
                ids = ids[keep].reshape(len(who), width)
                rank = rank[keep[:, 1:]].reshape(len(who), width - 1)  # the pair at `best` goes
                for first in (best - 1, best):
                    ok = np.flatnonzero((first >= 0) & (first < width - 1))
                    rank[ok, first[ok]] = self.pair_ranks(ids[ok, first[ok]], ids[ok, first[ok] + 1])
        return out

    def pieces(self, texts: list[bytes]) -> list[list[bytes]]:
        """The pieces of each text."""
        full = [i for i, t in enumerate(texts) if t]
        out: list[list[bytes]] = [[] for _ in texts]
        if not full:
            return out
        whole = b"".join(texts)
        raw = np.frombuffer(whole, np.uint8)
        lead = (raw & 0xC0) != 0x80
        at = np.flatnonzero(lead)  # byte offset of each code point
        points = np.frombuffer(whole.decode("utf-8").encode("utf-32-le"), "<u4")
        sizes = np.fromiter((len(texts[i]) for i in full), np.int64, len(full))
        byte_ends = np.cumsum(sizes)
        ends = np.searchsorted(at, byte_ends)  # code points before the end
        begin = np.concatenate(([0], ends[:-1]))
        flags = self.finder.starts(points, begin, ends - 1)
        cut = at[np.flatnonzero(flags)]
        bounds = np.concatenate((cut, [len(whole)])).tolist()
        first = np.searchsorted(cut, np.concatenate(([0], byte_ends))).tolist()
        all_pieces = [whole[a:b] for a, b in zip(bounds, bounds[1:], strict=False)]
        for n, i in enumerate(full):
            out[i] = all_pieces[first[n] : first[n + 1]]
        return out

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """Each text's ids as little-endian 32-bit numbers. Bytes that are no UTF-8 count as U+FFFD, as a decoder would show them."""
        split = self.pieces(valid(texts))
        if len(self.cache) > self.cache_size:
            self.cache = dict(self.seed)
        cache = self.cache
        new = list({p for ps in split for p in ps if p not in cache})
        for i in range(0, len(new), 50_000):
            cache.update(self.merge_many(new[i : i + 50_000]))
        return [b"".join(map(cache.__getitem__, ps)) for ps in split]


def valid(texts: list[bytes]) -> list[bytes]:
    """The texts with U+FFFD in place of what is no UTF-8."""
    try:
        b"\n".join(texts).decode()
    except UnicodeDecodeError:
        return [t.decode("utf-8", "replace").encode() for t in texts]
    return texts


class Decoder:
    """Ids back to bytes, with the byte offset at which each id's bytes begin."""

    def __init__(self, ranks: dict[bytes, int]):
        n = max(ranks.values(), default=-1) + 1
        self.size = np.zeros(n, np.int64)
        parts = [b""] * n
        for t, i in ranks.items():
            self.size[i], parts[i] = len(t), t
        self.start = np.concatenate(([0], np.cumsum(self.size)))[:-1]
        self.pool = np.frombuffer(b"".join(parts), np.uint8)

    def decode(self, ids: np.ndarray) -> tuple[bytes, np.ndarray]:
        size = self.size[ids]
        offset = np.concatenate(([0], np.cumsum(size)))
        where = np.repeat(self.start[ids] - offset[:-1], size) + np.arange(offset[-1])
        return self.pool[where].tobytes(), offset[:-1]


def read_ranks(path: str) -> dict[bytes, int]:
    """The tokens and ids of a rank file: a base64 token and a number on each line."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


#: The encoder and decoder that a worker process keeps from task to task, by the digest of their vocabulary.
_KEPT: dict[str, tuple[Encoder, Decoder]] = {}


def digest(ranks: dict[bytes, int]) -> str:
    """A digest of every token and id."""
    h = hashlib.sha256()
    for token, i in ranks.items():
        h.update(b"%d:%d:" % (i, len(token)) + token)
    return h.hexdigest()


def _held(key: str, ranks: dict[bytes, int]) -> tuple[Encoder, Decoder]:
    if key not in _KEPT:
        _KEPT.clear()
        _KEPT[key] = Encoder(ranks), Decoder(ranks)
    return _KEPT[key]


def encode(docs: DataFrame, ranks: dict[bytes, int], digests: bool = False, ids: bool = True) -> DataFrame:
    """doc_id and n_tokens, with `ids` arrays of ids and offsets (each id's first byte), with `digests` hashes of the ids and of the decoded bytes.

    The vocabulary is a broadcast of bounded size: that of the rank file.
    """
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast((digest(ranks), ranks))

    def make():
        encoder, decoder = _held(*sent.value)

        def work(texts):
            out = encoder.encode(texts)
            found = {"n_tokens": [len(x) // 4 for x in out]}
            back = [decoder.decode(np.frombuffer(x, "<u4")) for x in out]
            if digests:
                found["ids_sha256"] = [hashlib.sha256(x).hexdigest() for x in out]
                found["decoded_sha256"] = [hashlib.sha256(x).hexdigest() for x, _ in back]
            if ids:
                found["ids"], found["offsets"] = [np.frombuffer(x, "<i4") for x in out], [at for _, at in back]
            return found

        return work

    schema = "n_tokens long" + ", ids_sha256 string, decoded_sha256 string" * digests + ", ids array<int>, offsets array<long>" * ids
    return per_text(id_and_bytes(docs), schema, make)


def decode(encoded: DataFrame, ranks: dict[bytes, int]) -> DataFrame:
    """doc_id and text of a frame of doc_id and ids; ids null: an empty text."""
    sent = encoded.sparkSession.sparkContext.broadcast((digest(ranks), ranks))

    def run(frames: Iterable):
        decoder = _held(*sent.value)[1]
        for f in frames:
            f["text"] = [decoder.decode(np.asarray(x if x is not None else [], np.int64))[0].decode("utf-8", "replace") for x in f["ids"]]
            yield f[["doc_id", "text"]]

    return encoded.select("doc_id", "ids").mapInPandas(run, "doc_id long, text string")


def op6_bpe_codec(spark: SparkSession, sf_dir: str, path: str | None = None) -> DataFrame:
    """Every whole text encoded and decoded again, as digests."""
    return encode(table(spark, sf_dir, "documents"), read_ranks(path or default_path()), digests=True, ids=False)


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")
