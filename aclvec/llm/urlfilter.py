"""URL filters: rules by host and path, and boosted trees on lexical features for the rest.

All of it is DataFrame expressions: features, bins, histograms and the trees'
scores. Training rows are the URLs that a rule judges; they are binned, equal
rows are counted once, and each level of a tree needs one aggregation of
gradients by leaf, feature and bin. Only these histograms reach the driver.

Suffix statistics are smoothed shares of blocked URLs by top-level suffix, by
the last two labels of the host, by first path segment and by file ending, of
all values that `LEAST` training rows have. They are a table of at most
`SAMPLE` / `LEAST` rows for each kind, joined by value from a broadcast.

Defined results: a null URL, or one without `://`, has an empty host and path
and is judged by the trees like any other; without training rows all that no
rule judges is allowed; of two rules the longer one wins, and of equally long
ones the first; a score of one half or more blocks. Repeated rows give repeated
rows. Extra columns are left alone, but for those named like a result (host,
path, rule, rule_verdict, score, verdict), which the result replaces.
"""

from __future__ import annotations

import math
from collections import defaultdict

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.llm.common import sampled, stored, table

SAMPLE, LEAST, BINS, TREES, DEPTH, RATE = 100_000, 2, 12, 10, 3, 0.3
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Rules (verdict, host, path).
RULES = [("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/")]
NUMBERS = ("url_length", "host_length", "path_length", "host_depth", "path_depth", "digit_ratio", "entropy", "n_params", "n_special")
KINDS = ("top_suffix", "two_suffix", "first_segment", "ending")


def with_host_and_path(urls: DataFrame) -> DataFrame:
    """Adds host and path."""
    at = F.instr("url", "://")
    rest = F.when(at > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise("")
    host = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)
    return urls.withColumns({"host": F.coalesce(F.translate(host, UPPER, LOWER), F.lit("")), "path": F.coalesce(path, F.lit(""))})


def with_rule(urls: DataFrame, rules: list[tuple[str, str, str]] = RULES) -> DataFrame:
    """Adds rule (the longest that fits, else null) and rule_verdict. The rules are a list given by the user, compiled into one expression."""
    text, verdict = F, F
    for i, (says, host, path) in enumerate(sorted(rules, key=lambda r: -len(r[1] + r[2]))):
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(path)
        text, verdict = text.when(fits, F.lit(host + path)), verdict.when(fits, F.lit(says))
    none = F.lit(None).cast("string")
    return urls.withColumns({"rule": text if rules else none, "rule_verdict": verdict if rules else none})


def with_features(urls: DataFrame) -> DataFrame:
    """Adds the columns of NUMBERS and KINDS."""
    url = F.coalesce("url", F.lit(""))
    n = F.greatest(F.length(url), F.lit(1))
    query = F.regexp_extract(url, r"\?([^#]*)", 1)
    chars = F.array_distinct(F.split(url, ""))
    share = lambda c: (F.length(url) - F.length(F.replace(url, c, F.lit("")))) / n
    labels = F.split("host", r"\.")
    return urls.withColumns({
        "url_length": F.length(url).cast("double"),
        "host_length": F.length("host").cast("double"),
        "path_length": F.length("path").cast("double"),
        "host_depth": F.size(labels).cast("double"),
        "path_depth": F.length(F.regexp_replace("path", "[^/]", "")).cast("double"),
        "digit_ratio": F.length(F.regexp_replace(url, "[^0-9]", "")) / n,
        "entropy": F.aggregate(F.filter(chars, lambda c: c != ""), F.lit(0.0), lambda acc, c: acc - share(c) * F.log2(F.greatest(share(c), F.lit(1e-9)))),
        "n_params": F.when(query == "", 0.0).otherwise(1.0 + F.length(F.regexp_replace(query, "[^&]", ""))),
        "n_special": F.length(F.regexp_replace(url, "[A-Za-z0-9/:.]", "")).cast("double"),
        "top_suffix": F.element_at(labels, -1),
        "two_suffix": F.concat_ws(".", F.slice(labels, F.greatest(F.size(labels) - 1, F.lit(1)), 2)),
        "first_segment": F.regexp_extract("path", "^/([^/]*)/", 1),
        "ending": F.translate(F.regexp_extract("path", r"\.([A-Za-z0-9]{1,8})$", 1), UPPER, LOWER),
    })


class Model:
    """Suffix shares, bin edges and trees. A tree: a list of levels, each leaf -> (feature, bin), and values of leaves."""

    def __init__(self):
        self.prior, self.n = 0.5, 0
        self.shares: DataFrame | None = None  # kind, value, share
        self.edges: dict[str, list[float]] = {}
        self.base, self.trees = 0.0, []

    def with_shares(self, rows: DataFrame) -> DataFrame:
        """Suffixes as their shares of blocked URLs, in place of their text."""
        for k in KINDS:
            known = self.shares.filter(F.col("kind") == k).select(F.col("value").alias(k), F.col("share").alias(f"share_{k}"))
            rows = rows.join(F.broadcast(known), k, "left").withColumn(k, F.coalesce(f"share_{k}", F.lit(self.prior))).drop(f"share_{k}")  # SAMPLE / LEAST rows
        return rows

    def bins(self) -> dict[str, Column]:
        """Each feature's bin: the number of edges that it exceeds."""
        return {f"bin_{f}": sum((F.when(F.col(f) > e, 1).otherwise(0) for e in edges), F.lit(0)) for f, edges in self.edges.items()}

    def leaf(self, levels: list[dict[int, tuple[str, int]]]) -> Column:
        """The leaf that a binned row reaches."""
        at = F.lit(0)
        for level in levels:
            go = F.lit(0)
            for node, (f, cut) in level.items():
                go = F.when(at == node, F.when(F.col(f"bin_{f}") > cut, 1).otherwise(0)).otherwise(go)
            at = at * 2 + go
        return at

    def raw(self) -> Column:
        """The log odds of a block, over binned rows."""
        out = F.lit(self.base)
        for levels, values in self.trees:
            out = out + self._value(levels, values, 0, 0)
        return out

    def _value(self, levels, values, depth: int, node: int) -> Column:
        if depth == len(levels):
            return F.lit(float(values.get(node, 0.0)))
        low, high = (self._value(levels, values, depth + 1, 2 * node + side) for side in (0, 1))
        if node not in levels[depth]:
            return low
        f, cut = levels[depth][node]
        return F.when(F.col(f"bin_{f}") > cut, high).otherwise(low)


def train(judged: DataFrame) -> Model:
    """Boosted trees from URLs with a rule's verdict (`rule_verdict`)."""
    model = Model()
    total = judged.count()
    rows = sampled(judged, total, SAMPLE, key="url").withColumn("y", F.when(F.col("rule_verdict") == "block", 1.0).otherwise(0.0))
    rows = stored(with_features(rows).select("y", *NUMBERS, *KINDS))
    first = rows.agg(F.count("*").alias("n"), F.sum("y").alias("y")).first()
    if not first.n:
        return model
    model.n, model.prior = first.n, (first.y + 1) / (first.n + 2)
    model.base = math.log(model.prior / (1 - model.prior))
    values = F.explode(F.array(*(F.struct(F.lit(k).alias("kind"), F.col(k).alias("value")) for k in KINDS))).alias("s")
    counted = rows.select(values, "y").groupBy("s.kind", "s.value").agg(F.count("*").alias("n"), F.sum("y").alias("y")).filter(F.col("n") >= LEAST)
    model.shares = stored(counted.select("kind", "value", ((F.col("y") + 5 * model.prior) / (F.col("n") + 5)).alias("share")))
    rows = stored(model.with_shares(rows))
    cuts = rows.agg(*(F.percentile_approx(f, [i / BINS for i in range(BINS)], 10_000).alias(f) for f in (*NUMBERS, *KINDS)), *(F.max(f).alias(f"top_{f}") for f in (*NUMBERS, *KINDS))).first()
    model.edges = {f: sorted({x for x in cuts[f] if x < cuts[f"top_{f}"]}) for f in (*NUMBERS, *KINDS)}
    model.edges = {f: e for f, e in model.edges.items() if e}
    names = list(model.edges)
    if not names:  # all training URLs look alike: the base alone
        return model
    binned = rows.select("y", *(c.alias(n) for n, c in model.bins().items()))
    cells = stored(binned.groupBy(*(f"bin_{f}" for f in names)).agg(F.count("*").alias("n"), F.sum("y").alias("y")))
    for _ in range(TREES):
        levels: list[dict[int, tuple[str, int]]] = []
        p = 1 / (1 + F.exp(-model.raw()))
        graded = cells.select("*", (F.col("y") - F.col("n") * p).alias("g"), (F.col("n") * p * (1 - p)).alias("h"))
        leaves: dict[int, float] = {}
        for depth in range(DEPTH):
            spread = graded.select(model.leaf(levels).alias("leaf"), "g", "h", F.explode(F.array(*(F.struct(F.lit(f).alias("f"), F.col(f"bin_{f}").alias("b")) for f in names))).alias("s"))
            grid: dict = defaultdict(lambda: defaultdict(dict))
            for r in spread.groupBy("leaf", "s.f", "s.b").agg(F.sum("g").alias("g"), F.sum("h").alias("h")).collect():
                grid[r.leaf][r.f][r.b] = (r.g, r.h)
            level, leaves = {}, {}
            for leaf in sorted(grid):
                best = split(grid[leaf])
                if best is None:
                    g, h = (sum(v[i] for v in grid[leaf][names[0]].values()) for i in (0, 1))
                    leaves[2 * leaf] = RATE * g / (h + 1)
                    continue
                (f, cut), sides = best
                level[leaf] = (f, cut)
                for side, (g, h) in enumerate(sides):
                    leaves[2 * leaf + side] = RATE * g / (h + 1)
            levels.append(level)
        model.trees.append((levels, leaves))
    return model


def split(histograms: dict[str, dict[int, tuple[float, float]]], least: float = 1.0) -> tuple | None:
    """The (feature, bin) at which a leaf gains most, with the sums of both sides."""
    best, found = 1e-6, None
    for f in sorted(histograms):
        cells = sorted(histograms[f].items())
        g_all, h_all = (sum(v[i] for _, v in cells) for i in (0, 1))
        g = h = 0.0
        for b, (x, y) in cells[:-1]:
            g, h = g + x, h + y
            gain = g * g / (h + 1) + (g_all - g) ** 2 / (h_all - h + 1) - g_all**2 / (h_all + 1)
            if gain > best + 1e-9 and min(h, h_all - h) >= least:
                best, found = gain, ((f, b), ((g, h), (g_all - g, h_all - h)))
    return found


def judge(urls: DataFrame, model: Model) -> DataFrame:
    """Adds score (of a block) and verdict to URLs with rules."""
    if not model.n:
        return urls.withColumns({"score": F.lit(0.0), "verdict": F.coalesce("rule_verdict", F.lit("allow"))})
    # The caller's columns travel apart, so that none of them meets a feature's name.
    own = urls.select(F.struct(*(F.col(f"`{c}`") for c in urls.columns)).alias("own"), "url", "host", "path")
    rows = model.with_shares(with_features(own).select("own", *NUMBERS, *KINDS))
    binned = rows.select("own", *(c.alias(n) for n, c in model.bins().items()))
    scored = binned.select(*(F.col(f"own.`{c}`").alias(c) for c in urls.columns if c != "score"), (1 / (1 + F.exp(-model.raw()))).alias("score"))
    return scored.withColumn("verdict", F.coalesce("rule_verdict", F.when(F.col("score") >= 0.5, "block").otherwise("allow")))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The verdict on every URL: its rule's, else the trees'."""
    ruled = with_rule(with_host_and_path(table(spark, sf_dir, "pages").select("page_id", "url")))
    model = train(ruled.filter("rule is not null"))
    return judge(ruled, model).select("page_id", "host", "path", "rule", "verdict", "score")
