"""Language-model scoring by a hidden Markov model over words, beside a smoothed unigram base.

Tokens are words and a closing end. Every training token is counted. The end,
every word seen `OWN` times at least, and the `TOP` most frequent words even if
they are rarer, are symbols of their own, so the alphabet grows with the
vocabulary (at most `TOP` + tokens / `OWN` words). All other words, unknown ones
too, fall into `GROUPS` groups by their last bytes. A state emits a symbol, a
group then emits its word by the word's share among the group's counts (0.1 is
added to each, and to one place for unknown words), so the model is a
distribution over token sequences.

Every round of Baum-Welch runs over all training documents: tasks sum expected
counts, one aggregation adds them up. Rounds end when the log likelihood of a
token rises by less than `GAIN`. Texts of more than `SEGMENT` tokens are cut into
segments whose transfer matrices are multiplied, so that likelihoods are exact
and no loop follows a long text word by word.

Texts are read once and kept as blocks: the distinct words of about `BLOCK_BYTES`
of text, and each token as its word's place among them. Counts and symbols are
then fetched once for each block and distinct word; the `TOP` words, which nearly
every block asks for, come from a broadcast, so that no join key is hot.

Defined results: a null or empty text is the end alone; a row without an id is
held out; without training documents every count is 0 and all tokens are
unknown. Repeated rows give repeated rows.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from aclvec.llm.common import chunks, crc_mod, id_and_bytes, stored, table

TOP, OWN, GROUPS, STATES, TAIL = 2_000, 50, 512, 4, 3
#: Nats a token: the rise of the log likelihood below which training ends.
GAIN = 0.0001
ADD, UNIT = 0.1, 1_000_000
SEGMENT, BLOCK_BYTES = 512, 16 << 20
#: Steps between two scalings of a recursion; columns of an array that stay in a core's cache.
SCALE, PIECE = 8, 16_384
#: Groups come first, then the end, then words of their own.
END = GROUPS
#: Parts in which words of their own are numbered, for each power of two of their counts.
PARTS = 256


def words_of(text: bytes) -> list[bytes]:
    return text.lower().split()


def group_of(word: bytes) -> int:
    return zlib.crc32(word[-TAIL:]) % GROUPS


class Model:
    """Start and moves of the states, and the symbols that each emits."""

    def __init__(self, start: np.ndarray, move: np.ndarray, emit: np.ndarray):
        self.start, self.move, self.emit = start, move, emit

    @classmethod
    def first(cls, symbol_counts: np.ndarray, states: int = STATES, seed: int = 7) -> Model:
        """States that differ a little around the symbols' shares and tend to stay."""
        rng = np.random.default_rng(seed)
        share = (symbol_counts + 0.5) / (symbol_counts + 0.5).sum()
        emit = share[:, None] * np.exp(rng.normal(0, 0.7, (len(share), states)))
        move = np.full((states, states), 0.1 / max(1, states - 1))
        np.fill_diagonal(move, 0.9 if states > 1 else 1.0)
        return cls(np.full(states, 1 / states), move, emit / emit.sum(axis=0))

    def updated(self, start: np.ndarray, move: np.ndarray, emit: np.ndarray, share: np.ndarray) -> Model:
        """The next model from expected counts; the symbols' shares smooth the emissions."""
        start, move = start + 0.1, move + 0.1
        emit = emit + 20 * share[:, None]
        return Model(start / start.sum(), move / move.sum(axis=1, keepdims=True), emit / emit.sum(axis=0))


class Segments:
    """Symbol sequences cut into segments, longest first."""

    def __init__(self, seqs: list[np.ndarray]):
        sizes = np.fromiter(map(len, seqs), np.int64, len(seqs))
        flat = np.concatenate(seqs).astype(np.int32)
        self.parts = parts = -(-sizes // SEGMENT)
        self.first = np.cumsum(parts) - parts
        self.n_texts, self.long = len(seqs), np.flatnonzero(parts > 1)
        self.text = np.repeat(np.arange(len(seqs)), parts)
        nr = np.arange(len(self.text)) - self.first[self.text]
        begin = (np.cumsum(sizes) - sizes)[self.text] + nr * SEGMENT
        size = np.minimum(sizes[self.text] - nr * SEGMENT, SEGMENT)
        self.order = np.argsort(-size, kind="stable")
        # Symbols step by step; at each step the segments that reach it, longest first, are a prefix.
        alive = len(size) - np.searchsorted(np.sort(size), np.arange(int(size.max(initial=0))), side="right")
        ends = np.concatenate(([0], np.cumsum(alive))).tolist()
        begin = begin[self.order]
        self.symbols = np.empty(ends[-1], np.int32)
        for t, n in enumerate(alive.tolist()):
            np.take(flat, begin[:n], out=self.symbols[ends[t] : ends[t + 1]], mode="clip")
            begin[:n] += 1
        self.steps = [(t, n, slice(ends[t], ends[t + 1])) for t, n in enumerate(alive.tolist())]
        self.sub = Segments([seqs[i] for i in self.long.tolist()]) if len(self.long) and len(self.long) < len(seqs) else self if len(self.long) else None


class Scaled:
    """A model with each symbol's emissions divided by their largest, in the type of the recursions."""

    def __init__(self, model: Model, dtype):
        top = model.emit.max(axis=1)
        self.logs = np.log(top)
        self.emit = np.ascontiguousarray((model.emit / top[:, None]).astype(dtype))
        self.start, self.move = model.start.astype(dtype), model.move.astype(dtype)
        self.turn = np.ascontiguousarray(self.move.T)

    def of(self, cut: Segments) -> np.ndarray:
        """Each state's emissions of the symbols, state first."""
        out = np.empty((self.emit.shape[1], len(cut.symbols)), self.emit.dtype)
        for i in range(0, out.shape[1], PIECE):
            out[:, i : i + PIECE] = self.emit.take(cut.symbols[i : i + PIECE], axis=0).T
        return out


def transfer(model: Scaled, cut: Segments) -> np.ndarray:
    """Each segment's transfer matrix, up to a factor."""
    k, n, emit = len(model.start), len(cut.text), model.of(cut)
    m = np.repeat(np.eye(k, dtype=emit.dtype)[:, :, None], n, axis=2)
    for t, a, at in cut.steps:
        np.multiply(np.matmul(model.turn, m[:, :, :a]), emit[None, :, at], out=m[:, :, :a])
        if t % SCALE == SCALE - 1:
            m[:, :, :a] /= m[:, :, :a].max(axis=(0, 1))
    out = np.empty((n, k, k), emit.dtype)
    out[cut.order] = m.transpose(2, 0, 1)
    return out


def borders(model: Scaled, cut: Segments) -> tuple[np.ndarray, np.ndarray]:
    """For each segment the chances of the states before it, and how well each state after it explains the rest of its text, up to a factor."""
    k = len(model.start)
    enter, leave = np.tile(model.start, (len(cut.text), 1)), np.ones((len(cut.text), k), model.start.dtype)
    if not len(cut.long):
        return enter, leave
    m, first, parts = transfer(model, cut.sub), cut.sub.first, cut.parts[cut.long]
    own = cut.first[cut.long]  # where the long texts' segments begin among all
    now = enter[own]
    for j in range(int(parts.max())):
        who = np.flatnonzero(parts > j)
        enter[own[who] + j] = now[who]
        x = np.einsum("ni,nij->nj", now[who], m[first[who] + j])
        now[who] = x / x.sum(axis=1, keepdims=True)
    now = np.ones((len(own), k), model.start.dtype)
    for j in range(int(parts.max()) - 1, -1, -1):
        who = np.flatnonzero(parts > j)
        leave[own[who] + j] = now[who]
        x = np.einsum("nij,nj->ni", m[first[who] + j], now[who])
        now[who] = x / x.sum(axis=1, keepdims=True)
    return enter, leave


def forward(model: Scaled, cut: Segments, emit: np.ndarray, enter: np.ndarray, left: np.ndarray | None = None) -> np.ndarray:
    """The log likelihood of each segment after the states `enter`, without its symbols' scales; into `left` the states before each step."""
    now = np.ascontiguousarray(enter[cut.order].T)
    logs = np.zeros(len(cut.text))
    for t, a, at in cut.steps:
        now = now[:, :a]
        if left is not None:
            left[:, at] = now
        now = (model.turn @ now) * emit[:, at]
        stay = cut.steps[t + 1][1] if t + 1 < len(cut.steps) else 0
        if t % SCALE == SCALE - 1:
            s = now.sum(axis=0)
            now /= s
            logs[:a] += np.log(s)
        if stay < a:
            logs[stay:a] += np.log(now[:, stay:].sum(axis=0))
    out = np.empty(len(logs))
    out[cut.order] = logs
    return out


def likelihood(model: Model, seqs: list[np.ndarray]) -> np.ndarray:
    """The natural log likelihood of each sequence."""
    cut, scaled = Segments(seqs), Scaled(model, np.float64)
    logs = forward(scaled, cut, scaled.of(cut), borders(scaled, cut)[0])
    return np.bincount(cut.text, logs, cut.n_texts) + np.array([scaled.logs[s].sum() for s in seqs])


def expected(model: Model, seqs: list[np.ndarray], dtype=np.float32) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Baum-Welch counts of some texts: start, moves, emissions; and their log likelihood."""
    cut, scaled = Segments(seqs), Scaled(model, dtype)
    emit = scaled.of(cut)
    enter, leave = borders(scaled, cut)
    # States before each step and chances of what follows it, each up to a factor.
    left, right = np.empty_like(emit), np.empty_like(emit)
    logs = forward(scaled, cut, emit, enter, left)
    back = np.ascontiguousarray(leave[cut.order].T)
    for t, a, at in reversed(cut.steps):
        np.multiply(emit[:, at], back[:, :a], out=right[:, at])
        back[:, :a] = scaled.move @ right[:, at]
        if t % SCALE == 0:
            back[:, :a] /= back[:, :a].sum(axis=0)
    place = np.empty(len(cut.order), np.int64)
    place[cut.order] = np.arange(len(cut.order))
    start = scaled.start[:, None] * back[:, place[cut.first]]
    start = (start / start.sum(axis=0)).sum(axis=1, dtype=float)
    pairs, state = np.zeros_like(model.move), emit  # whose emissions are needed no more
    for i in range(0, emit.shape[1], PIECE):
        l, r, s = (x[:, i : i + PIECE] for x in (left, right, state))
        np.multiply(scaled.turn @ l, r, out=s)
        weight = s.sum(axis=0)
        s /= weight
        r /= weight
        pairs += l @ r.T
    counts = np.stack([np.bincount(cut.symbols, row, len(model.emit)) for row in state], axis=1)
    return start, model.move * pairs, counts, float(logs.sum() + scaled.logs[cut.symbols].sum())


def packed(docs: DataFrame) -> DataFrame:
    """Blocks of texts: their ids and sizes, each token's place among the block's distinct words, these words with their groups and counts in training texts."""

    def run(batches):
        schema = pa.schema([
            ("block", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("held", pa.list_(pa.bool_())), ("sizes", pa.list_(pa.int64())),
            ("places", pa.binary()), ("words", pa.list_(pa.binary())), ("groups", pa.binary()), ("train", pa.list_(pa.int64())),
        ])
        for b in batches:
            ids, held = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("doc_id", "held_out"))
            for rows, texts in chunks(b, limit=BLOCK_BYTES):
                number: dict[bytes, int] = {}
                put, parts = number.setdefault, []
                for t in texts:
                    ws = words_of(t)
                    parts.append(np.fromiter((put(w, len(number)) for w in ws), np.uint32, len(ws)))
                places = np.concatenate(parts)
                train = np.repeat(~np.array(held[rows]), list(map(len, parts)))
                count = np.bincount(places[train], minlength=len(number))
                groups = np.fromiter(map(group_of, number), np.uint16, len(number))
                tag = hashlib.blake2b(repr((ids[rows], held[rows])).encode() + places.tobytes() + b" ".join(number), digest_size=8).digest()
                yield pa.RecordBatch.from_pydict({
                    "block": [int.from_bytes(tag, "little", signed=True)], "doc_ids": [ids[rows]], "held": [held[rows]], "sizes": [[len(x) for x in parts]],
                    "places": [pa.compress(places.tobytes(), "zstd", asbytes=True)], "words": [list(number)], "groups": [groups.tobytes()], "train": [count],
                }, schema)

    schema = "block long, doc_ids array<long>, held array<boolean>, sizes array<long>, places binary, words array<binary>, groups binary, train array<long>"
    return id_and_bytes(docs, "held_out").mapInArrow(run, schema)


def word_counts(blocks: DataFrame) -> DataFrame:
    """word and its count in the training texts."""
    words = blocks.select(F.explode(F.arrays_zip("words", "train")).alias("x")).select("x.words", F.col("x.train").alias("c"))
    return words.filter("c > 0").groupBy(F.col("words").alias("word")).agg(F.sum("c").alias("c"))


def asked_words(blocks: DataFrame, words: DataFrame, top: DataFrame) -> DataFrame:
    """block, place, c and symbol of each block's distinct words that training texts hold; `top`: the most frequent ones, few rows."""
    asked = blocks.select(F.col("block").alias("block"), F.posexplode("words").alias("place", "word"))
    few = F.broadcast(top)  # TOP rows
    often = asked.join(few, "word")
    rest = asked.join(few, "word", "left_anti").join(words, "word")
    return often.unionByName(rest).select("block", "place", "c", "symbol")


def coded(blocks: DataFrame, counts: DataFrame, known: dict) -> DataFrame:
    """Per document: base score, log10 share within groups, and the symbols of its tokens."""
    sent = blocks.sparkSession.sparkContext.broadcast(known)

    def run(key, rows, counts):
        k = sent.value
        size, total = k["size"], k["total"]
        end = np.log10((k["n_train"] + ADD) / (total + ADD * (size + 1)))
        at = counts["place"].to_numpy()
        out = {x: [] for x in ("doc_id", "held_out", "n_tokens", "n_known", "base_score", "inner", "symbols")}
        for r in rows.to_pylist():
            symbol = np.frombuffer(r["groups"], np.uint16).astype(np.uint32)
            c = np.zeros(len(symbol))
            c[at], symbol[at] = counts["c"].to_numpy(), counts["symbol"].to_numpy()
            base = np.log10((c + ADD) / (total + ADD * (size + 1)))
            own = symbol > END
            g = np.where(own, 0, symbol)
            inner = np.where(own, 0.0, np.log10((c + ADD) / (k["group_c"][g] + ADD * (k["group_v"][g] + 1))))
            sizes = np.array(r["sizes"], np.int64)
            places = np.frombuffer(pa.decompress(r["places"], 4 * int(sizes.sum()), "zstd"), np.uint32)
            ends = np.cumsum(sizes)
            full = np.flatnonzero(sizes)
            sums = np.zeros((3, len(sizes)))
            if len(full):
                sums[:, full] = [np.add.reduceat(x[places], (ends - sizes)[full]) for x in (base, inner, (c > 0).astype(float))]
            seq = symbol[places]
            out["doc_id"] += r["doc_ids"]
            out["held_out"] += r["held"]
            out["n_tokens"] += (sizes + 1).tolist()
            out["n_known"] += (sums[2].astype(np.int64) + (k["n_train"] > 0)).tolist()
            out["base_score"] += (sums[0] + end).tolist()
            out["inner"] += sums[1].tolist()
            last = np.array([END], np.uint32).tobytes()
            out["symbols"] += [seq[e - n : e].tobytes() + last for n, e in zip(sizes.tolist(), ends.tolist(), strict=True)]
        return pa.table(out, schema=arrow)

    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, inner double, symbols binary"
    arrow = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("inner", pa.float64()), ("symbols", pa.binary())])
    return blocks.drop("words", "train").groupBy("block").cogroup(counts.groupBy("block")).applyInArrow(run, schema)


def runs_of(batch: pa.RecordBatch, limit: int = 500_000):
    """Rows whose symbols are about `limit` together, as arrays."""
    for rows, parts in chunks(batch, "symbols", 4 * limit):
        yield rows, [np.frombuffer(x, np.uint32) for x in parts]


def round_counts(rows: DataFrame, model: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Expected counts and log likelihood of all rows: each task's sums, added up as integers of 1 / `UNIT`, the same in any order.

    A row holds the states' counts of one thing: a symbol, then each state left, the start, and the likelihood.
    """
    sent = rows.sparkSession.sparkContext.broadcast(model)
    k, n = len(model.start), len(model.emit)
    names = [f"s{i}" for i in range(k)]

    def run(batches):
        total = np.zeros((n + k + 2, k))
        for b in batches:
            for _, seqs in runs_of(b):
                start, move, emit, logp = expected(sent.value, seqs)
                total[:n] += emit
                total[n : n + k] += move
                total[n + k] += start
                total[n + k + 1, 0] += logp
        cells = np.flatnonzero(total.any(axis=1))
        values = np.round(total[cells] * UNIT).astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(cells, pa.int64()), *(pa.array(values[:, i]) for i in range(k))], names=["cell", *names])

    schema = "cell long, " + ", ".join(f"{x} long" for x in names)
    got = rows.select("symbols").mapInArrow(run, schema).groupBy("cell").agg(*(F.sum(x).alias(x) for x in names)).toPandas()
    sent.destroy()
    out = np.zeros((n + k + 2, k))
    out[got["cell"].to_numpy(np.int64)] = got[names].to_numpy(np.int64) / UNIT
    return out[n + k], out[n : n + k], out[:n], float(out[n + k + 1, 0])


def train_model(rows: DataFrame, symbol_counts: np.ndarray, n_train: int) -> Model:
    """Baum-Welch over all training documents, until a round's gain in likelihood is small."""
    model, share = Model.first(symbol_counts), (symbol_counts + 0.5) / (symbol_counts + 0.5).sum()
    before = -np.inf
    while n_train:
        *sums, logp = round_counts(rows, model)
        model = model.updated(*sums, share)
        if logp - before < GAIN * symbol_counts.sum():
            break
        before = logp
    return model


def with_symbols(vocabulary: DataFrame) -> tuple[DataFrame, DataFrame, np.ndarray]:
    """word, c and its symbol; the same of the `TOP` words; and the counts of the symbols of their own, in order."""
    least = vocabulary.orderBy(F.desc("c"), "word").limit(TOP).agg(F.max(F.struct(-F.col("c"), "word")).alias("x")).select((-F.col("x.col1")).alias("c"), "x.word").first()
    if least.c is None:
        none = vocabulary.withColumn("symbol", F.lit(0))
        return none, none, np.zeros(0)
    first = (F.col("c") > least.c) | ((F.col("c") == least.c) & (F.col("word") <= F.lit(bytearray(least.word))))
    own = (F.col("c") >= OWN) | first
    # Frequent words get small numbers, which lie together in memory; a word's number depends on its count and bytes alone.
    part = (62 - F.floor(F.log2("c"))) * PARTS + F.crc32("word") % PARTS
    numbered = vocabulary.filter(own).withColumn("p", part.cast("int"))
    numbered = stored(numbered.withColumn("nr", F.row_number().over(Window.partitionBy("p").orderBy("word"))))
    sizes = sorted(tuple(r) for r in numbered.groupBy("p").count().collect())  # 63 * PARTS rows at most
    before = np.cumsum([0, *(n for _, n in sizes)]).tolist()
    offset = F.broadcast(vocabulary.sparkSession.createDataFrame([(p, b) for (p, _), b in zip(sizes, before, strict=False)], "p int, before long"))
    numbered = numbered.join(offset, "p").select("word", "c", first.alias("often"), (F.col("before") + F.col("nr") + F.lit(END)).cast("int").alias("symbol"))
    top, numbered = numbered.filter("often").drop("often"), numbered.drop("often")
    got = numbered.select("symbol", "c").toPandas()
    counts = np.zeros(before[-1])
    counts[got["symbol"].to_numpy() - END - 1] = got["c"].to_numpy()
    others = vocabulary.filter(~own).withColumn("symbol", (F.crc32(F.substring("word", -TAIL, TAIL)) % GROUPS).cast("int"))
    return others.unionByName(numbered), top, counts


def score_texts(docs: DataFrame, held_out) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of all documents; `held_out`: a condition."""
    blocks = stored(packed(docs.withColumn("held_out", F.coalesce(held_out, F.lit(True))).select("doc_id", "text", "held_out")), "zstd")
    n_train = blocks.select(F.explode("held").alias("h")).filter("not h").count()
    vocabulary = stored(word_counts(blocks))
    total, size = vocabulary.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    words, top, own_counts = with_symbols(vocabulary)
    group_c, group_v = np.zeros(GROUPS), np.zeros(GROUPS)
    for r in words.filter(F.col("symbol") < GROUPS).groupBy("symbol").agg(F.sum("c").alias("c"), F.count("*").alias("v")).collect():
        group_c[r.symbol], group_v[r.symbol] = r.c, r.v
    symbol_counts = np.concatenate((group_c, [n_train], own_counts))
    known = {"total": total + n_train, "size": size + (n_train > 0), "n_train": n_train, "group_c": group_c, "group_v": group_v}
    rows = stored(coded(blocks, asked_words(blocks, words, top), known), "zstd")
    model = train_model(rows.filter("not held_out"), symbol_counts, n_train)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            for part, seqs in runs_of(b):
                cols = b.slice(part.start, part.stop - part.start)
                get = lambda c: cols.column(cols.schema.get_field_index(c))
                score = likelihood(sent.value, seqs) / np.log(10) + get("inner").to_numpy()
                yield pa.RecordBatch.from_arrays([get("doc_id"), get("held_out"), get("n_tokens"), get("n_known"), pa.array([known["total"]] * len(seqs), pa.int64()), get("base_score"), pa.array(score)], names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return rows.mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op5_hmm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Log10 probabilities of every whole text, learned from the documents that are not held out."""
    return score_texts(table(spark, sf_dir, "documents"), crc_mod("doc_id", 10) == 0)
