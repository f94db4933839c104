"""Quality rules: a linear-chain conditional random field marks each line as content or boilerplate.

Lines become rows of binary features; Viterbi decoding runs over all texts of a
batch at once, line by line. A text is kept if the words of its content lines
are at least `SHARE` of its words and it passes the base rules.

The field is trained on the driver from a bounded sample of labelled documents
(`SAMPLE` documents with `LINES` lines at most). A line has the label that most
of the sampled documents holding it have; ties, and so all lines of one document
alone, go to its own document's label (0: boilerplate, 1: content). So labels
change within texts, and the field learns when.

Defined results: a null or empty text has no words and fails the base rules;
without labels every line is content; ties go to content. Repeated rows give
repeated rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from aclvec.llm.common import chunks, crc_mod, id_and_bytes, joined, per_text, sampled, table

SAMPLE, LINES, SHARE = 6_000, 1_000_000, 0.5
MIN_WORDS, MAX_REPEAT_PERCENT, WINDOW = 10, 20, 5
FEATURES = 24


def is_space() -> np.ndarray:
    out = np.zeros(256, bool)
    out[[32, 9, 10, 11, 12, 13]] = True
    return out


def byte_kinds() -> np.ndarray:
    """0 other, 1 lower, 2 upper, 3 digit, 4 symbol, 5 blank, 6 exclamation mark, 7 sentence mark, 8 at sign or slash."""
    out = np.zeros(256, np.uint8)
    out[ord("a") : ord("z") + 1] = 1
    out[ord("A") : ord("Z") + 1] = 2
    out[ord("0") : ord("9") + 1] = 3
    out[[ord(c) for c in "#*$%&|<>"]] = 4
    out[is_space()] = 5
    out[ord("!")] = 6
    out[[ord(c) for c in ".?:;\"'"]] = 7
    out[[ord("@"), ord("/")]] = 8
    return out


class Lines:
    """The lines of a run of texts: bounds, words and binary features."""

    def __init__(self, texts: list[bytes]):
        buf, self.begins = joined(texts)
        ends = np.flatnonzero(buf == 10)
        self.starts = np.concatenate(([0], ends[:-1] + 1))
        self.ends = ends
        self.first = np.searchsorted(self.starts, self.begins[:-1])  # each text's first line
        self.counts = np.diff(np.concatenate((self.first, [len(ends)])))
        kinds = byte_kinds()[buf]
        space = is_space()[buf]
        head = ~space
        head[1:] &= space[:-1]
        self.head = head
        per_line = lambda mask: np.add.reduceat(mask, self.starts, dtype=np.int64)
        self.words = per_line(head)
        self.by_kind = np.stack([per_line(kinds == k) for k in range(9)], axis=1)
        self.lead = ~space & ((buf & 0xC0) != 0x80)
        self.chars = np.add.reduceat(self.lead, self.begins[:-1], dtype=np.int64)
        self.symbols = np.add.reduceat(kinds == 4, self.begins[:-1], dtype=np.int64)
        self.text_words = np.add.reduceat(head, self.begins[:-1], dtype=np.int64)
        whole = buf.tobytes()
        self.lines = [whole[a:b] for a, b in zip(self.starts.tolist(), ends.tolist(), strict=True)]
        self.again = np.zeros(len(ends), bool)
        words = self.words.tolist()
        for f, n in zip(self.first.tolist(), self.counts.tolist(), strict=True):
            seen: set[bytes] = set()
            for i in range(f, f + n):
                line = self.lines[i]
                if line in seen:
                    self.again[i] = words[i] > 0
                seen.add(line)
        solid = np.where(space, -1, np.arange(len(buf)))
        last = np.maximum.reduceat(solid, self.starts)
        self.last_kind = np.where(last >= 0, kinds[last], 5)
        self.first_kind = kinds[self.starts]

    def features(self) -> np.ndarray:
        """(lines, FEATURES) of booleans."""
        k, w = self.by_kind, self.words
        solid = np.maximum(k.sum(axis=1) - k[:, 5], 1)
        share = lambda j: k[:, j] / solid
        size = solid / np.maximum(w, 1)
        at_first, at_last = np.zeros(len(w), bool), np.zeros(len(w), bool)
        at_first[self.first] = True
        at_last[self.first + self.counts - 1] = True
        marks = k[:, 6] / np.maximum(w, 1)
        symbols = k[:, 4] / np.maximum(w, 1)
        return np.stack([
            np.ones(len(w), bool), w == 0, (w > 0) & (w < 3), (w >= 3) & (w < 6), (w >= 6) & (w < 13), w >= 13,
            np.isin(self.last_kind, (6, 7)), self.first_kind == 2, symbols > 0, symbols > 0.2, symbols > 1,
            share(2) > 0.15, share(2) > 0.5, share(3) > 0.1, marks > 0.1, marks > 0.8, (size > 9) & (w > 0), (size < 3.5) & (w > 0),
            self.again, k[:, 8] > 1, at_first, at_last, share(7) > 0.1, share(0) > 0.5,
        ], axis=1)


def repeated_words(texts: list[bytes]) -> list[int]:
    """For each text, the words that lie in a window of `WINDOW` words found twice or more in it."""
    ids: dict[bytes, int] = {}
    number = ids.setdefault
    words = [t.split() for t in texts]
    sizes = [len(w) for w in words]
    seq = np.fromiter((number(x, len(ids)) for w in words for x in w), np.int64, sum(sizes))
    n = len(seq) - WINDOW + 1
    out = np.zeros(len(texts), np.int64)
    if n <= 0:
        return out.tolist()
    which = np.repeat(np.arange(len(texts)), sizes)
    inside = np.flatnonzero(which[:n] == which[WINDOW - 1 :])  # windows within one text
    h = which.astype(np.uint64)[inside]
    for k in range(WINDOW):
        h = (h ^ seq[inside + k].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    order = np.argsort(h, kind="stable")
    at = inside[order]
    same = (h[order][1:] == h[order][:-1]) & (which[at[1:]] == which[at[:-1]])
    pairs = np.flatnonzero(same)
    for k in range(WINDOW):  # equal hashes are checked word by word
        pairs = pairs[seq[at[pairs] + k] == seq[at[pairs + 1] + k]]
    hit = np.zeros(len(seq), bool)
    for k in range(WINDOW):
        hit[at[pairs] + k] = True
        hit[at[pairs + 1] + k] = True
    np.add.at(out, which[hit], 1)
    return out.tolist()


def by_step(first: np.ndarray, counts: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each step t: the sequences longer than t (ordered by length, longest first) and the rows of their t-th lines."""
    order = np.argsort(-counts, kind="stable")
    left = np.sort(counts)
    return [(order[: len(counts) - np.searchsorted(left, t, side="right")], first[order[: len(counts) - np.searchsorted(left, t, side="right")]] + t) for t in range(int(counts.max(initial=0)))]


class Field:
    """Weights of the two labels (0: content, 1: boilerplate). `mixed`: the share of training texts with lines of both."""

    mixed = 0.0

    def __init__(self, weight: np.ndarray | None = None, move: np.ndarray | None = None):
        self.weight = np.zeros((FEATURES, 2)) if weight is None else weight
        self.move = np.zeros((2, 2)) if move is None else move

    def decode(self, x: np.ndarray, first: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Viterbi: the best label of each line, for all sequences at once."""
        emit = x @ self.weight
        steps = by_step(first, counts)
        back = np.zeros((len(x), 2), np.int8)
        best = np.zeros((len(counts), 2))
        for t, (who, row) in enumerate(steps):
            if t == 0:
                best[who] = emit[row]
                continue
            ways = best[who][:, :, None] + self.move[None]
            back[row] = ways.argmax(axis=1)
            best[who] = ways.max(axis=1) + emit[row]
        label = np.zeros(len(x), np.int8)
        state = best.argmax(axis=1)
        for t in range(len(steps) - 1, -1, -1):
            who, row = steps[t]
            label[row] = state[who]
            if t:
                state[who] = back[row, state[who]]
        return label

    def train(self, x: np.ndarray, y: np.ndarray, first: np.ndarray, counts: np.ndarray, rounds: int = 60, rate: float = 0.2, ridge: float = 1e-3) -> Field:
        """Ascent on the penalised conditional likelihood, by forward and backward sums."""
        x = x.astype(float)
        steps = by_step(first, counts)
        one_hot = np.eye(2)[y]
        goal = x.T @ one_hot
        inner = np.ones(len(x), bool)
        inner[first] = False
        later = np.flatnonzero(inner)
        goal_move = np.bincount(y[later - 1] * 2 + y[later], minlength=4).reshape(2, 2)
        m, v = [np.zeros_like(self.weight), np.zeros_like(self.move)], [np.zeros_like(self.weight), np.zeros_like(self.move)]
        for r in range(1, rounds + 1):
            emit = np.exp(np.clip(x @ self.weight, -30, 30))
            emit /= emit.sum(axis=1, keepdims=True)
            move = np.exp(self.move)
            alpha, beta = np.zeros((len(x), 2)), np.ones((len(x), 2))
            for t, (_, row) in enumerate(steps):
                a = emit[row] if t == 0 else (alpha[row - 1] @ move) * emit[row]
                alpha[row] = a / a.sum(axis=1, keepdims=True)
            for t in range(len(steps) - 1, 0, -1):
                row = steps[t][1]
                b = (beta[row] * emit[row]) @ move.T
                beta[row - 1] = b / b.sum(axis=1, keepdims=True)
            node = alpha * beta
            node /= node.sum(axis=1, keepdims=True)
            edge = alpha[later - 1][:, :, None] * move[None] * (emit[later] * beta[later])[:, None, :]
            edge /= edge.sum(axis=(1, 2), keepdims=True)
            grads = [(goal - x.T @ node) / len(x) - ridge * self.weight, (goal_move - edge.sum(axis=0)) / len(x) - ridge * self.move]
            for k, w in enumerate((self.weight, self.move)):
                m[k] = 0.9 * m[k] + 0.1 * grads[k]
                v[k] = 0.99 * v[k] + 0.01 * grads[k] ** 2
                w += rate * (m[k] / (1 - 0.9**r)) / (np.sqrt(v[k] / (1 - 0.99**r)) + 1e-8)
        return self


def line_code(line: bytes) -> int:
    """64 bits of a line without blanks at its ends, in lower case; 0 for one without words."""
    key = line.strip().lower()
    return int.from_bytes(hashlib.blake2b(key, digest_size=8).digest(), "little", signed=True) if key else 0


def line_labels(code: np.ndarray, text: np.ndarray, quality: np.ndarray) -> np.ndarray:
    """1 (boilerplate) or 0 for each line: the label of most texts that hold it, its own text's where as many have either."""
    pairs, back = np.unique(np.stack((code, text), axis=1), axis=0, return_inverse=True)
    keys, at = np.unique(pairs[:, 0], return_inverse=True)
    votes = np.bincount(at, np.where(quality[pairs[:, 1]] == 0, 1, -1), len(keys))[at][back.ravel()]
    own = quality[text] == 0
    return np.where((votes == 0) | (code == 0), own, votes > 0).astype(int)


def train(docs: DataFrame, labels: DataFrame) -> Field:
    """A field from a bounded sample of labelled documents."""
    known = labels.filter(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", F.col("quality").cast("int").alias("quality"))
    few = F.broadcast(sampled(known, known.count(), SAMPLE, salt=23))  # SAMPLE rows of two numbers

    def run(batches):
        for b in batches:
            quality = np.array(b.column(b.schema.get_field_index("quality")).to_pylist(), np.int32)
            for rows, texts in chunks(b):
                lines = Lines(texts)
                bits = np.packbits(lines.features(), axis=1, bitorder="little")
                parts = [slice(f, f + n) for f, n in zip(lines.first.tolist(), lines.counts.tolist(), strict=True)]
                code = np.fromiter(map(line_code, lines.lines), np.int64, len(lines.lines))
                yield pa.RecordBatch.from_pydict({"quality": quality[rows], "bits": [bits[p].tobytes() for p in parts], "code": [code[p].tobytes() for p in parts]}, pa.schema([("quality", pa.int32()), ("bits", pa.binary()), ("code", pa.binary())]))

    own = docs.select("doc_id", "text").join(few, "doc_id")
    size = own.groupBy("doc_id").agg(F.sum(F.coalesce(F.size(F.split("text", "\n")), F.lit(1))).alias("n"))
    # A running sum over SAMPLE rows.
    fits = size.withColumn("n", F.sum("n").over(Window.orderBy(F.xxhash64("doc_id"), "doc_id"))).filter(F.col("n") <= LINES).select("doc_id")
    got = id_and_bytes(own, "quality").join(F.broadcast(fits), "doc_id").drop("doc_id").mapInArrow(run, "quality int, bits binary, code binary").toPandas()
    if not len(got):
        return Field()
    width = FEATURES // 8
    counts = got["bits"].map(len).to_numpy() // width
    x = np.unpackbits(np.frombuffer(b"".join(got["bits"]), np.uint8).reshape(-1, width), axis=1, bitorder="little")
    text, first = np.repeat(np.arange(len(counts)), counts), np.cumsum(counts) - counts
    y = line_labels(np.frombuffer(b"".join(got["code"]), np.int64), text, got["quality"].to_numpy())
    field = Field().train(x, y, first, counts)
    field.mixed = float((np.maximum.reduceat(y, first) != np.minimum.reduceat(y, first)).mean())
    return field


def judge(docs: DataFrame, field: Field) -> DataFrame:
    """Base counts, content share and verdict of every document."""
    sent = docs.sparkSession.sparkContext.broadcast(field)

    def work(texts):
        lines = Lines(texts)
        label = sent.value.decode(lines.features(), lines.first, lines.counts)
        sums = lambda v: np.add.reduceat(v, lines.first, dtype=np.int64)
        n, content = lines.text_words, sums(np.where(label == 0, lines.words, 0))
        repeat = np.array(repeated_words(texts))
        failed = (n < MIN_WORDS) | (100 * repeat > MAX_REPEAT_PERCENT * n)
        share = content / np.maximum(n, 1)
        return {
            "n_words": n, "word_chars": lines.chars, "n_symbols": lines.symbols, "n_dup_lines": sums(lines.again), "n_repeat_words": repeat,
            "base_failed": failed, "kept": ~failed & (share >= SHARE), "content_share": share,
        }

    schema = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, content_share double"
    return per_text(id_and_bytes(docs), schema, lambda: work)


def op4_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base counts and the verdict of the line labelling for every whole text."""
    docs = table(spark, sf_dir, "documents")
    return judge(docs, train(docs, table(spark, sf_dir, "labels").filter(crc_mod("doc_id", 4) != 2)))
