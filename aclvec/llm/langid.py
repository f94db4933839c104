"""Language identification by words first, then by shorter and shorter n-grams.

A known word adds its log frequency in each language. An unseen word is taken
apart: at each place the longest known character n-gram counts, from
`ORDERS[0]` characters down to one, each step down at a discount.

The model is learned from a bounded sample of labelled documents (`SAMPLE`
documents at most, by a hash of the id). Every language chooses its most frequent
words and n-grams of each order, seen `LEAST` times at least, within an equal
share of the budgets `WORDS` and `GRAMS`: the broadcast has a proven bound, and a
language's choice doesn't depend on how much text the others have. What one
language chose keeps its true counts in all.

Defined results: a null text, or one without a letter, is `und` with score 0;
ties go to the language that sorts first; without labelled documents all are
`und`. Repeated rows give repeated rows. Lang, source and id are no inputs.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.llm.common import chunks, crc_mod, id_and_bytes, per_text, sampled, stored, table

SAMPLE, WORDS, GRAMS = 20_000, 200_000, 100_000
ORDERS = (4, 3, 2, 1)
LEAST = 2
DISCOUNT, ALPHA = 0.4, 0.5
WORD = re.compile(r"[^\W\d_]+")
#: Unseen words of which a worker keeps the scores.
CACHE = 100_000


def words_of(text: bytes) -> list[str]:
    """Lower-case runs of letters."""
    return WORD.findall(text.decode("utf-8", "replace").lower())


def grams_of(word: str, n: int) -> list[str]:
    w = f"<{word}>"
    return [w[i : i + n] for i in range(len(w) - n + 1)]


def count_features(labelled: DataFrame) -> DataFrame:
    """lang, kind (0: word, n: n-gram), gram and n of labelled documents."""

    def run(batches):
        for b in batches:
            langs = b.column(b.schema.get_field_index("lang")).to_pylist()
            for rows, texts in chunks(b):
                words: dict[str, Counter] = defaultdict(Counter)
                for lang, t in zip(langs[rows], texts, strict=True):
                    words[lang].update(words_of(t))
                out = {k: [] for k in ("lang", "kind", "gram", "n")}
                for lang, count in words.items():
                    kinds = [(0, count)]
                    for n in ORDERS:
                        grams: Counter = Counter()
                        for w, c in count.items():
                            for g in grams_of(w, n):
                                grams[g] += c
                        kinds.append((n, grams))
                    for kind, c in kinds:
                        out["lang"] += [lang] * len(c)
                        out["kind"] += [kind] * len(c)
                        out["gram"] += list(c)
                        out["n"] += list(c.values())
                yield pa.RecordBatch.from_pydict(out, pa.schema([("lang", pa.string()), ("kind", pa.int32()), ("gram", pa.string()), ("n", pa.int64())]))

    counted = id_and_bytes(labelled, "lang").mapInArrow(run, "lang string, kind int, gram string, n long")
    return counted.groupBy("lang", "kind", "gram").agg(F.sum("n").alias("n"))


def chosen(counts: DataFrame, n_langs: int) -> DataFrame:
    """The counts, in all languages, of the words and n-grams that any language chose."""
    spark = counts.sparkSession
    # How many grams of a language have each count: at most about sqrt(2 x total) rows for each kind.
    sizes: dict[tuple, list] = defaultdict(list)
    for r in counts.filter(F.col("n") >= LEAST).groupBy("lang", "kind", "n").agg(F.count("*").alias("grams")).collect():
        sizes[r.lang, r.kind].append((r.n, r.grams))
    least = []
    for (lang, kind), found in sizes.items():
        room, lowest = (WORDS if kind == 0 else GRAMS // len(ORDERS)) // n_langs, None
        for n, grams in sorted(found, reverse=True):
            if (room := room - grams) < 0:
                break
            lowest = n
        if lowest is not None:
            least.append((lang, kind, lowest))
    least = F.broadcast(spark.createDataFrame(least, "lang string, kind int, least long"))  # one row a language and kind
    keys = counts.join(least, ["lang", "kind"]).filter("n >= least").select("kind", "gram").distinct()
    return counts.join(keys, ["kind", "gram"], "left_semi").select("lang", "kind", "gram", "n")


def train(labelled: DataFrame, n_rows: int) -> dict:
    """The model: languages, log frequencies of words and of n-grams."""
    counts = stored(count_features(sampled(labelled, n_rows, SAMPLE)))
    sums = {(r.lang, r.kind): (r.total, r.size) for r in counts.groupBy("lang", "kind").agg(F.sum("n").alias("total"), F.count("*").alias("size")).collect()}
    langs = sorted({lang for lang, _ in sums})
    rows = chosen(counts, len(langs)).toPandas()
    model: dict = {"langs": langs, "grams": {}}
    where = {x: i for i, x in enumerate(langs)}
    for kind in (0, *ORDERS):
        own = rows[rows["kind"] == kind]
        names = sorted(set(own["gram"]))
        row = {g: i for i, g in enumerate(names)}
        grid = np.zeros((len(names), len(langs)))
        grid[own["gram"].map(row).to_numpy(np.int64), own["lang"].map(where).to_numpy(np.int64)] = own["n"]
        size = max(1, len(names))
        n_l = np.array([sums.get((x, kind), (0, 0))[0] for x in langs], float)
        logs = (np.log(grid + ALPHA) - np.log(n_l + ALPHA * size)).astype(np.float32)
        # Only what tells languages apart matters: the mean over languages is taken out.
        logs -= logs.mean(axis=1, keepdims=True) if len(langs) else 0
        if kind == 0:
            model["words"] = (names, logs)
        else:
            model["grams"][kind] = dict(zip(names, logs, strict=True))
    return model


class Scorer(dict):
    """Words to rows of the score matrix; unseen words are scored together and kept for later texts."""

    def __init__(self, model: dict):
        self.names, logs = model["words"]
        super().__init__(zip(self.names, range(len(self.names)), strict=True))
        self.langs, self.known = model["langs"], len(self.names)
        self.words = self.rows = logs
        # One table of n-grams of all orders, at the discount of their order; row 0 is for none.
        self.grams: dict[str, int] = {}
        parts = [np.zeros((1, len(self.langs)), np.float32)]
        for step, k in enumerate(ORDERS):
            for g, v in model["grams"][k].items():
                self.grams[g] = len(self.grams) + 1
                parts.append(DISCOUNT**step * v[None])
        self.gram_rows = np.concatenate(parts)

    def learn(self, words: list[str]) -> None:
        """Adds the rows of unseen words: the mean over places of the longest known n-gram there."""
        get, found, sizes = self.grams.get, [], []
        for word in words:
            w = f"<{word}>"
            n = len(w)
            for i in range(n):
                for k in ORDERS:
                    if i + k <= n and (r := get(w[i : i + k])) is not None:
                        found.append(r)
                        break
                else:
                    found.append(0)
            sizes.append(n)
        at = np.concatenate(([0], np.cumsum(sizes)[:-1]))
        means = np.empty((len(words), len(self.langs)), np.float32)
        for i in range(0, len(words), 20_000):  # bounds the rows taken at a time
            j = min(i + 20_000, len(words))
            end = at[j] if j < len(words) else len(found)
            means[i:j] = np.add.reduceat(self.gram_rows[found[at[i] : end]], at[i:j] - at[i], axis=0) / np.array(sizes[i:j])[:, None]
        self.update(zip(words, range(len(self.rows), len(self.rows) + len(words)), strict=True))
        self.rows = np.concatenate((self.rows, means))

    def trim(self) -> None:
        if len(self) - self.known > CACHE:
            self.clear()
            self.update(zip(self.names, range(self.known), strict=True))
            self.rows = self.words

    def predict(self, texts: list[bytes]) -> tuple[list[str], list[float]]:
        if not self.langs:
            return ["und"] * len(texts), [0.0] * len(texts)
        words = [words_of(t) for t in texts]
        words = [w if any(c.isalpha() for x in w for c in x) else [] for w in words]
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        if new := list({x for w in words for x in w if x not in self}):
            self.learn(new)
        ids = np.fromiter((self[x] for w in words for x in w), np.int64, int(sizes.sum()))
        ends = np.concatenate(([0], np.cumsum(sizes)))
        sums = np.zeros((len(texts), len(self.langs)))
        full = np.flatnonzero(sizes)
        if len(full):
            sums[full] = np.add.reduceat(self.rows[ids].astype(np.float64), ends[full], axis=0)
        self.trim()
        mean = sums / np.maximum(sizes, 1)[:, None] * np.minimum(sizes, 30)[:, None]
        p = np.exp(mean - mean.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        best = p.argmax(axis=1)
        return ([self.langs[b] if n else "und" for b, n in zip(best.tolist(), sizes.tolist(), strict=True)], np.where(sizes > 0, p[np.arange(len(p)), best], 0.0).tolist())


def predict(docs: DataFrame, model: dict) -> DataFrame:
    """All columns of `docs` that are not text, with lang_pred and score."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        scorer = Scorer(sent.value)

        def work(texts):
            lang, score = scorer.predict(texts)
            return {"lang_pred": lang, "score": score}

        return work

    return per_text(docs, "lang_pred string, score double", make)


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every whole text, learned from the documents that are not held out."""
    docs = table(spark, sf_dir, "documents")
    known = docs.filter((crc_mod("doc_id", 4) != 2) & F.col("lang").isNotNull())
    model = train(known, known.select("doc_id").count())
    return predict(id_and_bytes(docs).withColumn("held_out", crc_mod("doc_id", 4) == 2), model)
