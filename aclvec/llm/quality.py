"""Quality classifier: a generalised additive model with pairwise interactions.

Shallow trees are boosted feature by feature in a cycle; each adds to the lookup
table of its one feature, so that the model is a table per feature and a small
grid per chosen pair. A score is a sum of table entries, found by the bins of a
text's features.

The model is fitted on a bounded sample of labelled documents (`SAMPLE` at
most, by a hash of the id) on the driver.

Defined results: a null or empty text has features of 0 and a score like any
other; without labels every score is 1 (nothing is known against a text);
a label that is null is no label; a document with several labels counts with
each. Labels, lang, source and id are no inputs of a score.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.llm.common import crc_mod, id_and_bytes, per_text, sampled, table

SAMPLE, BINS, PAIR_BINS, PAIRS, ROUNDS, RATE = 20_000, 32, 8, 6, 150, 0.15
THRESHOLD = 0.7
NAMES = (
    "letters", "upper", "digits", "blanks", "lines", "stops", "symbols", "other_punctuation", "high", "distinct_bytes",
    "word_length", "distinct_words", "short_words", "repeated_lines", "stopped_lines", "size", "capital_words", "line_length",
)


def byte_classes() -> np.ndarray:
    """A class for each byte."""
    out = np.full(256, 7, np.uint8)
    out[[*range(ord("a"), ord("z") + 1)]] = 0
    out[[*range(ord("A"), ord("Z") + 1)]] = 1
    out[[*range(ord("0"), ord("9") + 1)]] = 2
    out[[9, 11, 12, 13, 32]] = 3
    out[10] = 4
    out[[ord(c) for c in ".,;:?'\"()-"]] = 5
    out[[ord(c) for c in "#*$%&|<>"]] = 6
    out[128:] = 8
    return out


def features(texts: list[bytes]) -> np.ndarray:
    """A row of `NAMES` for each text."""
    kind = byte_classes()
    out = np.zeros((len(texts), len(NAMES)))
    for row, t in zip(out, texts, strict=True):
        if not t:
            continue
        counts = np.bincount(np.frombuffer(t, np.uint8), minlength=256)
        by = np.bincount(kind, counts, 9)
        n = len(t)
        words, lines = t.split(), [x for x in t.split(b"\n") if x.strip()]
        row[:9] = by / n
        row[0] += row[1]
        row[9] = np.count_nonzero(counts)
        row[15] = np.log1p(n)
        if words:
            sizes = np.fromiter(map(len, words), np.int64, len(words))
            row[10] = sizes.mean()
            row[11] = len(set(words)) / len(words)
            row[12] = np.count_nonzero(sizes <= 3) / len(words)
            row[16] = by[1] / len(words)
        if lines:
            row[13] = 1 - len(set(lines)) / len(lines)
            row[14] = sum(x.rstrip()[-1:] in b".!?:;\"'" for x in lines) / len(lines)
            row[17] = np.log1p(n / len(lines))
    return out


class Additive:
    """Edges and tables of features, grids of pairs."""

    def __init__(self, base: float, edges: list[np.ndarray], tables: list[np.ndarray], pairs: list[tuple[int, int]], grids: list[np.ndarray], coarse: list[np.ndarray]):
        self.base, self.edges, self.tables, self.pairs, self.grids, self.coarse = base, edges, tables, pairs, grids, coarse

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.base)
        for j, (e, t) in enumerate(zip(self.edges, self.tables, strict=True)):
            z += t[np.searchsorted(e, x[:, j], side="right")]
        for (a, b), g in zip(self.pairs, self.grids, strict=True):
            z += g[np.searchsorted(self.coarse[a], x[:, a], side="right"), np.searchsorted(self.coarse[b], x[:, b], side="right")]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def quantiles(x: np.ndarray, bins: int) -> np.ndarray:
    return np.unique(np.quantile(x, np.linspace(0, 1, bins + 1)[1:-1]))


def shallow(grad: np.ndarray, hess: np.ndarray, leaves: int = 3, smooth: float = 2.0) -> np.ndarray:
    """The step of a tree with up to `leaves` leaves over ordered bins."""
    cuts = [0, len(grad)]
    g, h = np.concatenate(([0], np.cumsum(grad))), np.concatenate(([0], np.cumsum(hess)))
    worth = lambda a, b: (g[b] - g[a]) ** 2 / (h[b] - h[a] + smooth)
    for _ in range(leaves - 1):
        best = (1e-9, None)
        for a, b in zip(cuts, cuts[1:], strict=False):
            if b - a > 1:
                c = np.arange(a + 1, b)
                gain = worth(a, c) + worth(c, b) - worth(a, b)
                if gain.max() > best[0]:
                    best = (gain.max(), int(c[gain.argmax()]))
        if best[1] is None:
            break
        cuts = sorted([*cuts, best[1]])
    out = np.zeros(len(grad))
    for a, b in zip(cuts, cuts[1:], strict=False):
        out[a:b] = (g[b] - g[a]) / (h[b] - h[a] + smooth)
    return out


def cross_tree(grad: np.ndarray, hess: np.ndarray, smooth: float = 2.0) -> np.ndarray:
    """The step of a tree that cuts a grid once along each side."""
    best, out = -1.0, np.zeros_like(grad)
    gc, hc = (np.pad(a.cumsum(0).cumsum(1), ((1, 0), (1, 0))) for a in (grad, hess))
    n, m = grad.shape
    for i in range(1, n):
        for j in range(1, m):
            boxes = [(0, i, 0, j), (0, i, j, m), (i, n, 0, j), (i, n, j, m)]
            sums = [[c[b, d] - c[a, d] - c[b, e] + c[a, e] for c in (gc, hc)] for a, b, e, d in boxes]
            gain = sum(g * g / (h + smooth) for g, h in sums)
            if gain > best:
                best = gain
                out = np.zeros_like(grad)
                for (a, b, e, d), (g, h) in zip(boxes, sums, strict=True):
                    out[a:b, e:d] = g / (h + smooth)
    return out


def fit(x: np.ndarray, y: np.ndarray) -> Additive:
    """Cyclic boosting of tables, then of the grids of the pairs that explain most of what is left."""
    d = x.shape[1]
    edges, coarse = [quantiles(x[:, j], BINS) for j in range(d)], [quantiles(x[:, j], PAIR_BINS) for j in range(d)]
    at = [np.searchsorted(edges[j], x[:, j], side="right") for j in range(d)]
    prior = (y.sum() + 1) / (len(y) + 2)
    base = float(np.log(prior / (1 - prior)))
    z, tables = np.full(len(y), base), [np.zeros(len(e) + 1) for e in edges]
    for _ in range(ROUNDS):
        for j in range(d):
            p = 1 / (1 + np.exp(-z))
            step = RATE * shallow(np.bincount(at[j], y - p, len(tables[j])), np.bincount(at[j], p * (1 - p), len(tables[j])))
            tables[j] += step
            z += step[at[j]]
    low = [np.searchsorted(coarse[j], x[:, j], side="right") for j in range(d)]
    p = 1 / (1 + np.exp(-z))
    gains = []
    grid = lambda a, b, w: np.bincount(low[a] * (len(coarse[b]) + 1) + low[b], w, (len(coarse[a]) + 1) * (len(coarse[b]) + 1)).reshape(len(coarse[a]) + 1, -1)
    for a in range(d):
        for b in range(a + 1, d):
            g, h = grid(a, b, y - p), grid(a, b, p * (1 - p))
            gains.append((float((g * g / (h + 2)).sum()), a, b))
    pairs = [(a, b) for _, a, b in sorted(gains, key=lambda t: (-t[0], t[1], t[2]))[:PAIRS]]
    grids = [np.zeros((len(coarse[a]) + 1, len(coarse[b]) + 1)) for a, b in pairs]
    for _ in range(ROUNDS // 10):
        for k, (a, b) in enumerate(pairs):
            p = 1 / (1 + np.exp(-z))
            step = RATE * cross_tree(grid(a, b, y - p), grid(a, b, p * (1 - p)))
            grids[k] += step
            z += step[low[a], low[b]]
    return Additive(base, edges, tables, pairs, grids, coarse)


def with_features(frame: DataFrame) -> DataFrame:
    return per_text(frame, "x array<double>", lambda: lambda texts: {"x": list(features(texts))})


def train(docs: DataFrame, labels: DataFrame) -> Additive | None:
    """A model of `labels.quality`, from a bounded sample of the labelled documents; None without labels."""
    known = labels.filter(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", F.col("quality").cast("int").alias("quality"))
    few = F.broadcast(sampled(known, known.count(), SAMPLE))  # SAMPLE rows of two numbers
    rows = with_features(id_and_bytes(docs).join(few, "doc_id")).select("quality", "x").toPandas()
    if not len(rows):
        return None
    return fit(np.array(rows["x"].tolist()), (rows["quality"].to_numpy() > 0).astype(float))


def predict(frame: DataFrame, model: Additive | None) -> DataFrame:
    """`frame` (with its bytes in `text`) with score and predicted in place of the text."""
    sent = frame.sparkSession.sparkContext.broadcast(model)

    def work(texts):
        m = sent.value
        score = np.ones(len(texts)) if m is None else m.score(features(texts))
        return {"score": score, "predicted": (score >= THRESHOLD).astype(np.int32)}

    return per_text(frame, "score double, predicted int", lambda: work)


def accepted(docs: DataFrame, model: Additive | None) -> DataFrame:
    """The rows of `docs`, with all their columns, whose text scores `THRESHOLD` or more."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def fine(texts: pd.Series) -> pd.Series:
        m = sent.value
        return pd.Series(np.ones(len(texts), bool) if m is None else m.score(features(texts.tolist())) >= THRESHOLD)

    return docs.filter(F.pandas_udf(fine, "boolean")(F.coalesce(F.col("text"), F.lit("")).cast("binary")))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A quality score for every whole text, learned from the labels of documents that are not held out."""
    docs = table(spark, sf_dir, "documents")
    labels = table(spark, sf_dir, "labels").filter(crc_mod("doc_id", 4) != 2)
    return predict(id_and_bytes(docs).withColumn("held_out", crc_mod("doc_id", 4) == 2), train(docs, labels))
