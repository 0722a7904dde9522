"""Threshold-scaled document fingerprints, in DataFrame functions only.

A text's sketch keeps every distinct shingle hash below a fixed fraction of the
hash range (one in ``2 ** SHIFT``), so sketches of unequal documents stay
comparable, merge by union, and estimate containment as well as resemblance.
Texts with few shingles would keep next to nothing; a sketch therefore also
keeps its ``FLOOR`` smallest hashes. Everything below a sketch's bound (the
fraction, or its last floor hash if that is higher, or all of it if it is
shorter than the floor) is complete, and two sketches are compared below the
lower bound of the two, which makes small texts exact.

Shingles are five lower-cased words (the whole text if shorter). Defined results:
null and empty texts have the empty sketch, which equals itself (likeness 1) and
nothing else (0); rows are ordered by id with nulls first, equal ids by a hash of
their texts; a single row follows itself.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tablemill.llm.common import stored

SHINGLE = 5
SHIFT = 4
FLOOR = 64
RANGES = 1 << 15
BELOW = -(1 << 63) + (1 << (64 - SHIFT))


def let(value: Column, fn: Callable[[Column], Column]) -> Column:
    """``fn(value)`` with the value computed once."""
    return F.transform(F.array(value), fn)[0]


def sketch(text: Column, shingle: int = SHINGLE) -> Column:
    """Sorted shingle hashes below the threshold, and the smallest ``FLOOR`` in any case."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[\\x09-\\x0D\\x20]+"), lambda w: w != "")
    hashed = F.transform(words, lambda w: F.xxhash64(w))
    runs = let(
        hashed,
        lambda h: F.when(F.size(h) == 0, F.expr("cast(array() as array<bigint>)")).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.size(h) - (shingle - 1), F.lit(1))), lambda i: F.xxhash64(F.slice(h, i, shingle)))),
    )
    return F.filter(F.sort_array(F.array_distinct(runs)), lambda x, i: (x < F.lit(BELOW)) | (i < FLOOR))


def bound(s: Column) -> Column:
    """The highest hash up to which a sketch is complete."""
    return F.when(F.size(s) < FLOOR, F.lit((1 << 63) - 1)).otherwise(F.greatest(F.lit(BELOW - 1), F.get(s, F.lit(FLOOR - 1))))


def compared(a: Column, b: Column, measure: Callable[[Column, Column, Column], Column]) -> Column:
    """``measure(common, size of a, size of b)`` below the lower bound of two sketches."""

    def below(top):
        return let(F.struct(F.filter(a, lambda x: x <= top).alias("a"), F.filter(b, lambda x: x <= top).alias("b")), lambda p: measure(F.size(F.array_intersect(p["a"], p["b"])), F.size(p["a"]), F.size(p["b"])))

    return let(F.least(bound(a), bound(b)), below)


def likeness(a: Column, b: Column) -> Column:
    """Estimated Jaccard similarity of two texts' shingle sets."""
    return compared(a, b, lambda both, m, n: F.when(m + n == 0, F.lit(1.0)).otherwise(both / (m + n - both)))


def containment(a: Column, b: Column) -> Column:
    """Estimated share of the shingles of ``a`` that ``b`` has."""
    return compared(a, b, lambda both, m, n: F.when(m == 0, F.lit(1.0)).otherwise(both / m))


def merged(a: Column, b: Column) -> Column:
    """Sketch of two texts' shingles together."""
    return F.filter(F.sort_array(F.array_union(a, b)), lambda x, i: (x < F.lit(BELOW)) | (i < FLOOR))


def fingerprint(s: Column) -> Column:
    """A sketch as text: 16 hexadecimal digits a hash."""
    return F.array_join(F.transform(s, lambda x: F.lpad(F.hex(x), 16, "0")), "")


def placed_in(cuts: Column, key: Column, steps: int) -> Column:
    """How many of the ascending ``cuts`` are not above ``key``: a binary search of ``steps`` halvings."""

    def halve(at, _):
        middle = F.floor((at["low"] + at["high"]) / 2).cast("int")
        above = F.get(cuts, middle) > key
        done = at["low"] >= at["high"]
        return F.struct(F.when(done | above, at["low"]).otherwise(middle + 1).alias("low"), F.when(done | ~above, at["high"]).otherwise(middle).alias("high"))

    start = F.struct(F.lit(0).alias("low"), F.size(cuts).alias("high"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, halve)["low"]


def with_next(docs: DataFrame, carried: list[str], per_range: int = 2000, most: int = RANGES) -> DataFrame:
    """``docs`` (doc_id, ...) with the ``carried`` columns of the next row in id order as ``next_<name>``; the first follows the last.

    Rows are cut into ranges of (id, hash of the first carried column), so neither
    ids nor nulls that many rows share make a range long. An exchange of these keys
    alone finds the least key of each range; the at most ``most`` least keys meet
    every row as one array, which a binary search reads. The rows of a range's least
    key also go, as sentinels, to the end of the range before, so no row needs more
    than its range, which is sorted on disk where it does not fit into memory.
    """
    tie = F.xxhash64(carried[0])
    keys = docs.select("doc_id", tie.alias("tie"))
    parts = max(1, min(most, -(-keys.count() // per_range)))
    least = keys.repartitionByRange(parts, "doc_id", "tie").groupBy(F.spark_partition_id().alias("p")).agg(F.min(F.struct("doc_id", "tie")).alias("key"))
    cuts = stored(least.agg(F.sort_array(F.collect_list("key")).alias("cuts")), "cuts")
    steps = parts.bit_length() + 8  # an exchange may be dealt out over somewhat more ranges than asked for
    ranged = docs.withColumn("tie", tie).withColumn("cuts", cuts.scalar()).withColumn("key", F.struct("doc_id", "tie"))
    ranged = ranged.withColumn("range", placed_in(F.col("cuts"), F.col("key"), steps))
    before = F.when(F.col("range") > 1, F.col("range") - 1).otherwise(F.size("cuts"))
    own, guest = (F.struct(r.alias("range"), F.lit(is_guest).alias("sentinel")) for r, is_guest in ((F.col("range"), False), (before, True)))
    is_first = F.get("cuts", F.col("range") - 1) == F.col("key")
    placed = ranged.withColumn("at", F.explode(F.when(is_first, F.array(own, guest)).otherwise(F.array(own)))).drop("cuts", "key", "range")
    order = Window.partitionBy("at.range").orderBy("at.sentinel", "doc_id", "tie")
    after = placed.withColumns({f"next_{c}": F.lead(c).over(order) for c in carried})
    return after.where("not at.sentinel").drop("tie", "at")


def op2_scaled_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    pairs = with_next(docs.withColumn("sketch", sketch(F.col("text"))), ["text", "sketch"])
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - half), F.substring("next_text", F.lit(1), half))
    made = pairs.select("doc_id", n.cast("long").alias("n_chars"), edited.alias("edited"), "sketch", "next_sketch")
    made = made.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "sketch", sketch(F.col("edited")).alias("edited_sketch"), "next_sketch")
    return made.select(
        "doc_id", "n_chars", "edited_sha256",
        fingerprint(F.col("sketch")).alias("fingerprint"), fingerprint(F.col("edited_sketch")).alias("edited_fingerprint"),
        likeness(F.col("sketch"), F.col("edited_sketch")).alias("near_edited"), likeness(F.col("sketch"), F.col("next_sketch")).alias("near_next"),
        containment(F.col("sketch"), F.col("edited_sketch")).alias("contained_edited"),
    )
