"""Mixing sources to target weights by temperature.

Source shares of tokens are raised to an exponent and normalised. The exponent
is the largest in [0, 1] at which the mix has the target entropy, or, where that
would repeat a source too often, the least at which it does not; it is found by
narrowing a grid, each step one aggregation over the sources. The weights are
realised for a budget of tokens: whole passes over a source and, for the rest,
the first tokens of a permutation of its blocks and of the documents in a block.
Blocks hold about `BLOCK` tokens, so a source of any size is dealt to many tasks.

By default the budget is the least that uses every document once.

Defined results: tokens are runs of other than ASCII white space; a null source
is a source; a document of a source without tokens is taken once; rows that
share an id are drawn alike, in order of their tokens; without documents there
is no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from aclvec.llm.common import stored, table

ENTROPY_SHARE, REPEATS, BLOCK = 0.95, 4.0, 250_000
STEPS, ROUNDS, SEED = 16, 5, 11


def n_words(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def name(source: str = "source") -> Column:
    """A source as a text that is never null."""
    return F.coalesce(F.concat(F.lit("s:"), F.col(source).cast("string")), F.lit("n"))


def temperature(sources: DataFrame, entropy_share: float = ENTROPY_SHARE, repeats: float = REPEATS, budget: int | None = None) -> float:
    """The exponent for sources (share), all above 0."""
    spark = sources.sparkSession

    def measured(alphas: list[float]) -> list:
        grid = spark.createDataFrame([(a,) for a in alphas], "alpha double")
        powers = sources.join(F.broadcast(grid)).withColumn("w", F.pow("share", "alpha"))  # a few exponents for each source
        sums = powers.groupBy("alpha").agg(F.sum("w").alias("z"), F.sum(F.col("w") * F.col("alpha") * F.ln("share")).alias("e"), F.max(F.col("w") / F.col("share")).alias("most"), F.min(F.col("w") / F.col("share")).alias("least"), F.count("*").alias("n"), F.sum("tokens").alias("t"))
        entropy = F.ln("z") - F.col("e") / F.col("z")
        repeat = F.col("most") / F.col("least") if budget is None else F.col("most") / F.col("z") * F.lit(float(budget)) / F.col("t")
        return sums.select("alpha", (entropy >= F.ln("n") * entropy_share - 1e-12).alias("even"), (repeat <= repeats + 1e-12).alias("fine")).orderBy("alpha").collect()

    def narrow(at_most: bool) -> float:
        """Grid search over i / STEPS**ROUNDS: the largest even exponent, or the least fine one."""
        low, unit = 0, STEPS**ROUNDS
        for r in range(1, ROUNDS + 1):
            step = STEPS ** (ROUNDS - r)
            rows = measured([(low + i * step) / unit for i in range(STEPS + 1)])
            good = [i for i, x in enumerate(rows) if (x.even if at_most else not x.fine)]
            if not good:
                return low / unit
            low += min(max(good), STEPS - (r < ROUNDS)) * step
        return low / unit if at_most else min(1.0, (low + 1) / unit)

    alpha = narrow(True)
    if not measured([alpha])[0].fine:
        alpha = narrow(False)
    return alpha


def draws(docs: DataFrame, entropy_share: float = ENTROPY_SHARE, repeats: float = REPEATS, budget: int | None = None) -> DataFrame:
    """doc_id, source, n_tokens, weight, copies and place (the first token's place in its source's permutation) of every document."""
    rows = stored(docs.select("doc_id", "source", name().alias("s"), n_words().alias("n_tokens")))
    sums = rows.groupBy("s").agg(F.sum("n_tokens").alias("tokens"))
    total = rows.agg(F.sum("n_tokens")).first()[0] or 0
    sources = stored(sums.filter("tokens > 0").withColumn("share", F.col("tokens") / F.lit(float(max(total, 1)))))
    alpha = temperature(sources, entropy_share, repeats, budget) if total else 1.0
    powers = sources.withColumn("w", F.pow("share", F.lit(alpha)))
    z, least = powers.agg(F.sum("w"), F.min(F.col("w") / F.col("share"))).first()
    # Passes over a source: weight x budget / its tokens; at least one each by the default budget.
    passes = F.col("w") / F.col("share") / F.lit(least or 1.0) if budget is None else F.col("w") / F.lit(z or 1.0) * F.lit(float(budget)) / F.col("tokens")
    plan = powers.select("s", (F.col("w") / F.lit(z or 1.0)).alias("weight"), F.floor(passes + 1e-9).alias("whole"), F.floor(F.greatest(passes + 1e-9 - F.floor(passes + 1e-9), F.lit(0.0)) * F.col("tokens")).alias("rest"), F.ceil(F.col("tokens") / BLOCK).alias("n_blocks"))
    plan = stored(plan)
    code = F.md5(F.concat_ws("|", F.lit(str(SEED)), F.coalesce(F.col("doc_id").cast("string"), F.lit("n"))).cast("binary"))
    placed = rows.join(plan, "s", "left").withColumn("code", code)
    placed = placed.withColumn("block", F.pmod(F.conv(F.substring("code", 1, 8), 16, 10).cast("long"), F.coalesce("n_blocks", F.lit(1))))
    blocks = placed.groupBy("s", "block").agg(F.sum("n_tokens").alias("block_tokens")).withColumn("block_code", F.md5(F.concat_ws("|", F.lit(str(SEED)), "s", F.col("block").cast("string")).cast("binary")))
    in_order = Window.partitionBy("s").orderBy("block_code", "block").rowsBetween(Window.unboundedPreceding, -1)
    blocks = blocks.select("s", "block", F.coalesce(F.sum("block_tokens").over(in_order), F.lit(0)).alias("before"))
    within = Window.partitionBy("s", "block").orderBy("code", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    placed = placed.withColumn("inside", F.coalesce(F.sum("n_tokens").over(within), F.lit(0))).join(blocks, ["s", "block"])
    place = F.col("before") + F.col("inside")
    copies = F.coalesce(F.col("whole") + F.when(place < F.col("rest"), 1).otherwise(0), F.lit(1))
    return placed.select("doc_id", "source", "n_tokens", F.coalesce("weight", F.lit(0.0)).alias("weight"), copies.cast("long").alias("copies"), place.alias("place"))


def mixed(docs: DataFrame, **how) -> DataFrame:
    """The rows of `docs`, each as often as it is drawn."""
    times = draws(docs, **how).groupBy(F.col("doc_id").alias("own_id")).agg(F.max("copies").cast("int").alias("own_copies"))
    both = docs.alias("d").join(times, F.col("d.doc_id").eqNullSafe(F.col("own_id"))).filter("own_copies > 0")
    repeated = both.select(F.struct(*(F.col(f"d.`{c}`") for c in docs.columns)).alias("own_row"), F.explode(F.sequence(F.lit(1), "own_copies")))
    return repeated.select("own_row.*")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often each whole document is drawn, and from which place of its source."""
    return draws(table(spark, sf_dir, "documents")).withColumn("weight", F.round("weight", 9))


def oracle() -> str:
    """The same mix in DuckDB: the grid search written out step by step."""
    unit = STEPS**ROUNDS
    parts = [f"""w AS (SELECT doc_id, source, coalesce('s:' || source, 'n') AS s, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0) AS n_tokens FROM documents),
src AS (SELECT s, sum(n_tokens) AS tokens, sum(n_tokens)::DOUBLE / (SELECT sum(n_tokens) FROM w) AS share FROM w GROUP BY s HAVING sum(n_tokens) > 0)"""]
    tests = {"e": f"ln(sum(p)) - sum(p * alpha * ln(share)) / sum(p) >= ln(count(*)) * {ENTROPY_SHARE} - 1e-12", "r": f"NOT (max(p / share) / min(p / share) <= {REPEATS} + 1e-12)"}
    for k, test in tests.items():
        parts.append(f"{k}0 AS (SELECT 0 AS low)")
        for r in range(1, ROUNDS + 1):
            step, most = STEPS ** (ROUNDS - r), STEPS - (r < ROUNDS)
            parts.append(f"""{k}{r} AS (SELECT (SELECT low FROM {k}{r - 1}) + coalesce(least(max(i), {most}), 0) * {step} AS low FROM (
  SELECT i, {test} AS good FROM (SELECT i, alpha, share, power(share, alpha) AS p FROM src, (SELECT i, ((SELECT low FROM {k}{r - 1}) + i * {step}) / {unit}::DOUBLE AS alpha FROM range({STEPS + 1}) t(i))) GROUP BY i, alpha) WHERE good)""")
    parts.append(f"""alphas AS (SELECT (SELECT low FROM e{ROUNDS}) / {unit}::DOUBLE AS ae, least(1.0, ((SELECT low FROM r{ROUNDS}) + 1) / {unit}::DOUBLE) AS ar),
a AS (SELECT CASE WHEN (SELECT max(power(share, ae) / share) / min(power(share, ae) / share) FROM src) <= {REPEATS} + 1e-12 THEN ae ELSE ar END AS alpha FROM alphas),
pw AS (SELECT s, tokens, share, power(share, (SELECT alpha FROM a)) AS p FROM src),
ps AS (SELECT *, p / share / (SELECT min(p / share) FROM pw) + 1e-9 AS passes, p / (SELECT sum(p) FROM pw) AS weight FROM pw),
plan AS (SELECT s, weight, floor(passes)::BIGINT AS whole, floor(greatest(passes - floor(passes), 0) * tokens)::BIGINT AS rest, ceil(tokens / {BLOCK}.0)::BIGINT AS n_blocks FROM ps),
placed AS (SELECT w.*, weight, whole, rest, md5('{SEED}|' || coalesce(doc_id::VARCHAR, 'n')) AS code, ('0x' || substr(md5('{SEED}|' || coalesce(doc_id::VARCHAR, 'n')), 1, 8))::BIGINT % coalesce(n_blocks, 1) AS block FROM w LEFT JOIN plan USING (s)),
blocks AS (SELECT s, block, coalesce(sum(t) OVER (PARTITION BY s ORDER BY md5('{SEED}|' || s || '|' || block::VARCHAR), block ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM (SELECT s, block, sum(n_tokens) AS t FROM placed GROUP BY ALL)),
inside AS (SELECT *, coalesce(sum(n_tokens) OVER (PARTITION BY s, block ORDER BY code, doc_id, n_tokens ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS inside FROM placed)
SELECT doc_id, source, n_tokens, round(coalesce(weight, 0.0), 9) AS weight, coalesce(whole + CASE WHEN before + inside < rest THEN 1 ELSE 0 END, 1)::BIGINT AS copies, (before + inside)::BIGINT AS place
FROM inside JOIN blocks USING (s, block)""")
    body = ",\n".join(parts)
    at = body.rindex("\nSELECT doc_id, source")
    return "WITH " + body[:at] + body[at:]
