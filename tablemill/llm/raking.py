"""Mixing sources to target weights by iterative proportional fitting.

Tokens are summed by cell (source, language, topic); each round scales the cells
so that one marginal after the other meets its target, until ``ROUNDS`` are over or
no marginal is further than ``tolerance`` from its target. What a document is
wanted for is ``keep * ratio`` of its cell, where ratio is the fitted share over
the share it had. Up to 1 that is its calibrated probability. Beyond 1 the whole part
is a number of certain copies and the rest the probability of one more, so that
the tokens of ``sampled`` meet the marginals in expectation without a weight to
carry. Draws compare the probability with a hash of the seed and the document id:
the same documents are drawn in any layout of the data.

Only cells, not documents, take part in the rounds; each sum is combined before
it is shuffled, so a source with a third of all rows is one row a task. Up to
``FEW_CELLS`` cells all rounds run as one task without an exchange; more of them
are dealt out. DataFrame functions only.

Targets default to shares in proportion to the square root of the tokens (a
temperature of 2), over the values that occur. A value with a target but no
token cannot be met; targets are scaled to those that occur. Defined results:
null source or language counts as the empty string; null and empty texts have
no token, are topic ``empty`` and have probability ``keep`` if their cell is
without tokens; repeated rows are drawn together.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tablemill.llm.common import forget, stored

DIMENSIONS = ("source", "lang", "topic")
ROUNDS = 12
FEW_CELLS = 200_000
KEEP = 0.8
SEED = "mix"
POWER = 0.5
WORD = r"[^\x09-\x0D\x20]+"


def topic(text: Column) -> Column:
    """A coarse subject from marks in the whole text; the first that applies."""
    return (
        F.when(F.coalesce(F.length(text), F.lit(0)) == 0, "empty")
        .when(text.contains("icensed under") | text.contains("MIT License") | text.contains("rights reserved"), "legal")
        .when(text.contains("@"), "contact")
        .when(text.contains(" | "), "tabular")
        .when(text.contains("!!"), "shouting")
        .when(F.length(text) < 600, "note")
        .otherwise("prose")
    )


def tokens(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def described(docs: DataFrame, kind: Column | None = None) -> DataFrame:
    """doc_id, source, lang, topic, n_tokens of every row."""
    text = F.col("text")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("source", F.lit("")).alias("source"), F.coalesce("lang", F.lit("")).alias("lang"), (topic(text) if kind is None else kind).alias("topic"), tokens(text).alias("n_tokens"))


def default_targets(cells: DataFrame, power: float = POWER) -> dict[str, DataFrame]:
    """(value, target) of each dimension: the tokens of each value to a power."""
    return {d: cells.groupBy(F.col(d).alias("value")).agg(F.pow(F.sum("n_tokens").cast("double"), F.lit(power)).alias("target")).where("target > 0") for d in DIMENSIONS}


def wanted(cells: DataFrame, targets: dict[str, DataFrame] | None, power: float = POWER) -> DataFrame:
    """``cells`` with ``share`` and, for each dimension, ``want_<d>``: the target share of its value (null without one)."""
    every = Window.partitionBy(F.lit(0))
    now = cells.withColumn("share", F.col("n_tokens") / F.greatest(F.sum("n_tokens").over(every), F.lit(1)).cast("double"))
    for d in DIMENSIONS:
        mine = Window.partitionBy(d)
        tokens_of = F.sum("n_tokens").over(mine).cast("double")
        if targets is None:
            now = now.withColumn("_target", F.when(tokens_of > 0, F.pow(tokens_of, F.lit(power))))
        else:
            now = now.join(targets[d].select(F.col("value").alias(d), F.col("target").alias("_target")), d, "left").withColumn("_target", F.when(tokens_of > 0, F.col("_target")))
        # A value's target counts once, at one of its cells.
        first = F.row_number().over(mine.orderBy(*DIMENSIONS)) == 1
        now = now.withColumn("_once", F.when(first, F.col("_target"))).withColumn(f"want_{d}", F.col("_target") / F.sum("_once").over(every)).drop("_target", "_once")
    return now


def gap(cells: DataFrame) -> float:
    """The largest distance between a marginal's fitted share and its target share."""
    far = [F.max(F.abs(F.col(f"have_{d}") - F.coalesce(f"want_{d}", F.lit(0.0)))) for d in DIMENSIONS]
    have = cells.withColumns({f"have_{d}": F.sum("share").over(Window.partitionBy(d)) for d in DIMENSIONS})
    return have.agg(reduce(F.greatest, far).alias("gap")).first().gap or 0.0


def fitted(cells: DataFrame, targets: dict[str, DataFrame] | None = None, rounds: int = ROUNDS, tolerance: float | None = None) -> DataFrame:
    """``cells`` (dimensions, n_tokens) with ``share``: their fitted part of all tokens."""
    few = cells.limit(FEW_CELLS + 1).count() <= FEW_CELLS
    cells = cells.select(*DIMENSIONS, "n_tokens")
    # A single partition meets the demand of every window below, so none of them shuffles.
    now = wanted(cells.coalesce(1) if few else cells, targets)
    for number in range(1, rounds + 1):
        for d in DIMENSIONS:
            have = F.sum("share").over(Window.partitionBy(d))
            now = now.withColumn("share", F.when(have > 0, F.col("share") * (F.coalesce(f"want_{d}", F.lit(0.0)) / have)).otherwise(0.0))
        if number % 6 == 0 or number == rounds:
            now = stored(now, "raked")
            if tolerance is not None and gap(now) <= tolerance:
                break
            now = now.coalesce(1) if few and number < rounds else now
    return now.select(*DIMENSIONS, "n_tokens", "share")


def hash_unit(*parts: Column) -> Column:
    """A number in [0, 1) from the first 32 bits of an md5."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("long") / F.lit(float(1 << 32))


def ratios(rows: DataFrame, targets: dict[str, DataFrame] | None = None, rounds: int = ROUNDS) -> DataFrame:
    """Cells with ``ratio``: the fitted share over the share they had (null without tokens)."""
    cells = stored(rows.groupBy(*DIMENSIONS).agg(F.sum("n_tokens").alias("n_tokens")), "cells")
    total = cells.agg(F.sum("n_tokens")).first()[0] or 0
    fit = fitted(cells, targets, rounds)
    forget(cells)
    return fit.withColumn("ratio", F.when(F.col("n_tokens") > 0, F.col("share") / (F.col("n_tokens") / F.lit(float(max(total, 1)))))).select(*DIMENSIONS, "share", "ratio")


def mixed(rows: DataFrame, targets: dict[str, DataFrame] | None = None, keep: float = KEEP, seed: str = SEED, rounds: int = ROUNDS) -> DataFrame:
    """``rows`` (as of ``described``) with ratio, probability, weight and sampled."""
    cells = ratios(rows, targets, rounds)
    want = F.lit(keep) * F.coalesce("ratio", F.lit(1.0))
    both = rows.join(cells.drop("share"), list(DIMENSIONS)).withColumn("probability", F.least(F.lit(1.0), want)).withColumn("weight", F.when(F.col("probability") > 0, want / F.col("probability")).otherwise(0.0))
    return both.withColumn("sampled", hash_unit(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) < F.col("probability"))


def sampled(docs: DataFrame, targets: dict[str, DataFrame] | None = None, keep: float = KEEP, seed: str = SEED, rounds: int = ROUNDS) -> DataFrame:
    """The sampled documents, with their columns as they were; a document wanted more than once comes as often as it is wanted."""
    cells = ratios(described(docs), targets, rounds)
    # The cells' columns get names that no document has; the draw needs nothing but the cell.
    names = {c: f"_cell_{c}" for c in (*DIMENSIONS, "ratio")}
    taken = {c.lower() for c in docs.columns}
    while any(n in taken for n in names.values()):
        names = {c: f"{n}_" for c, n in names.items()}
    cells = cells.select(*[F.col(c).alias(n) for c, n in names.items()])
    here = (F.coalesce(docs["source"], F.lit("")) == F.col(names["source"])) & (F.coalesce(docs["lang"], F.lit("")) == F.col(names["lang"])) & (topic(docs["text"]) == F.col(names["topic"]))
    want = F.lit(keep) * F.coalesce(F.col(names["ratio"]), F.lit(1.0))
    draw = hash_unit(F.lit(seed), F.coalesce(docs["doc_id"].cast("string"), F.lit(""))) < want - F.floor(want)
    times = (F.floor(want) + draw.cast("int")).cast("int")
    return docs.join(cells, here).where(times > 0).select(*[docs[f"`{c}`"] for c in docs.columns], F.explode(F.sequence(F.lit(1), times)).alias(names["ratio"])).drop(names["ratio"])


def op9_raked_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixed(described(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    return out.select("doc_id", "source", "lang", "topic", "n_tokens", F.round("ratio", 6).alias("ratio"), F.round("probability", 6).alias("probability"), F.round("weight", 6).alias("weight"), "sampled")


def op9_sql(rounds: int = ROUNDS, keep: float = KEEP, power: float = POWER, seed: str = SEED) -> str:
    """The same rounds, written out one after the other."""
    parts = [
        r"""d AS (SELECT doc_id, coalesce(source, '') AS source, coalesce(lang, '') AS lang,
       CASE WHEN coalesce(length(text), 0) = 0 THEN 'empty'
            WHEN contains(text, 'icensed under') OR contains(text, 'MIT License') OR contains(text, 'rights reserved') THEN 'legal'
            WHEN contains(text, '@') THEN 'contact' WHEN contains(text, ' | ') THEN 'tabular' WHEN contains(text, '!!') THEN 'shouting'
            WHEN length(text) < 600 THEN 'note' ELSE 'prose' END AS topic,
       len(regexp_extract_all(coalesce(text, ''), '[^\x09-\x0D\x20]+'))::BIGINT AS n_tokens FROM documents)""",
        "c0 AS (SELECT source, lang, topic, sum(n_tokens)::BIGINT AS n_tokens, sum(n_tokens)::DOUBLE / sum(sum(n_tokens)::DOUBLE) OVER () AS share FROM d GROUP BY ALL)",
    ]
    for dim in DIMENSIONS:
        parts.append(f"t_{dim} AS (SELECT {dim} AS value, pow(sum(n_tokens)::DOUBLE, {power}) AS target FROM c0 GROUP BY {dim} HAVING sum(n_tokens) > 0)")
    at = 0
    for _ in range(rounds):
        for dim in DIMENSIONS:
            parts.append(f"h{at} AS (SELECT value, target / sum(target) OVER () / have AS scale FROM (SELECT {dim} AS value, sum(share) AS have FROM c{at} GROUP BY {dim}) JOIN t_{dim} USING (value) WHERE have > 0)")
            parts.append(f"c{at + 1} AS (SELECT source, lang, topic, n_tokens, share * coalesce(scale, 0) AS share FROM c{at} LEFT JOIN h{at} ON {dim} = value)")
            at += 1
    parts.append(f"r AS (SELECT source, lang, topic, CASE WHEN n_tokens > 0 THEN share / (n_tokens / sum(n_tokens::DOUBLE) OVER ()) END AS ratio FROM c{at})")
    parts.append(f"p AS (SELECT d.*, ratio, {keep} * coalesce(ratio, 1) AS want, least(1.0, {keep} * coalesce(ratio, 1)) AS probability FROM d JOIN r USING (source, lang, topic))")
    return (
        "WITH " + ",\n".join(parts) + "\nSELECT doc_id, source, lang, topic, n_tokens, round(ratio, 6) AS ratio, round(probability, 6) AS probability, "
        "round(CASE WHEN probability > 0 THEN want / probability ELSE 0 END, 6) AS weight, "
        f"('0x' || substr(md5(concat_ws('|', '{seed}', coalesce(doc_id::VARCHAR, ''))), 1, 8))::BIGINT / 4294967296.0 < probability AS sampled FROM p"
    )
