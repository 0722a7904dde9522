"""Hierarchical language identification.

First a family is predicted, then one-versus-one linear support vector machines
tell the languages of that family apart. All machines are linear in counts of
hashed character n-grams inside words (one to four letters with word borders)
and of whole words, divided by their number; a text's value is therefore a sum
over its words, and each distinct word of a batch is scored only once.

Training takes a bounded sample: ``per_language`` labelled texts of each
language, by hash order, a repeated text once. Each machine is fitted in a task of
its own from the texts of its two sides (a family's side takes ``per_language``
texts in all, spread over its languages), so the driver sees weights only: one
row of ``BINS`` numbers a machine.

Defined results: ``und`` with score 0 for a null text or one without a letter;
a language without a family in ``FAMILIES`` is a family of its own; if no
labelled row exists, every text is ``und``. Ties go to the alphabetically first.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tablemill.llm.common import columns, lean, sums, trim
from tablemill.llm.pieces import gather, slices

# Families of language codes.
FAMILIES = {
    "germanic": ["af", "da", "de", "en", "is", "nb", "nl", "nn", "no", "sv"],
    "romance": ["ca", "es", "fr", "gl", "it", "oc", "pt", "ro"],
    "slavic": ["be", "bg", "bs", "cs", "hr", "mk", "pl", "ru", "sk", "sl", "sr", "uk"],
    "uralic": ["et", "fi", "hu"],
    "celtic": ["br", "cy", "ga", "gd"],
    "baltic": ["lt", "lv"],
    "semitic": ["ar", "he", "mt"],
    "turkic": ["az", "kk", "tr", "uz"],
}
FAMILY_OF = {lang: family for family, langs in FAMILIES.items() for lang in langs}

BINS = 1 << 13
ORDERS = (1, 2, 3, 4)
PER_LANGUAGE = 400
UNDETERMINED = "und"


# --- features --------------------------------------------------------------


def word_features(words: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Order by order, the hashed bins of the distinct words' features and the words they belong to, ascending.

    Words are lower-cased; bytes of any script count, but a word without a letter has no features.
    """
    low = pc.utf8_lower(words)
    size = pc.binary_length(low).to_numpy(zero_copy_only=False).astype(np.int64)
    lettered = pc.match_substring_regex(low, r"\pL").to_numpy(zero_copy_only=False)
    flat = np.frombuffer(b"".join(b"\x00" + w + b"\x00" for w in low.cast(pa.binary()).to_pylist()), np.uint8).astype(np.uint64)
    owner = np.repeat(np.arange(len(size), dtype=np.int32), size + 2)
    first = np.cumsum(size + 2) - size - 2
    whole = np.zeros(len(size), np.uint64)
    for n in ORDERS:
        if len(flat) < n:
            continue
        h = np.full(len(flat) - n + 1, n, np.uint64)
        for i in range(n):
            h ^= flat[i : len(flat) - n + 1 + i]
            h *= np.uint64(0x100000001B3)
            h ^= h >> np.uint64(29)
        keep = owner[: len(h)] == owner[n - 1 :]
        keep &= lettered[owner[: len(h)]]
        if n == 1:
            keep &= flat[: len(h)] != 0
        yield ((h[keep] >> np.uint64(7)) % np.uint64(BINS)).astype(np.int32), owner[: len(h)][keep]
        if n == 4:
            total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h), np.full(3, h.sum() if len(h) else 0, np.uint64)])
            stop = np.maximum(first + size - 1, first)
            whole = total[stop] - total[first]
    named = np.flatnonzero(lettered).astype(np.int32)
    yield (((whole[named] + size[named].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(17)) % np.uint64(BINS)).astype(np.int32), named


def texts_words(texts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Distinct words, the word numbers of all texts, and the number of words of each text."""
    words = pc.ascii_split_whitespace(pc.fill_null(texts.cast(pa.string()), ""))
    coded = words.flatten().dictionary_encode()
    return coded.dictionary, coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), np.diff(words.offsets.to_numpy().astype(np.int64))


def text_vectors(texts: pa.Array) -> np.ndarray:
    """Dense relative frequencies; for the bounded training sample only."""
    pool, index, counts = texts_words(texts)
    out = np.zeros((len(texts), BINS), np.float32)
    ends = np.cumsum(counts)
    used = [np.unique(index[e - n : e], return_counts=True) for e, n in zip(ends.tolist(), counts.tolist())]
    for bins, owner in word_features(pool):
        size = np.bincount(owner, minlength=len(pool))
        start = np.cumsum(size) - size
        for i, (word, times) in enumerate(used):
            out[i] += np.bincount(gather(bins, start[word], size[word]), weights=np.repeat(times, size[word]), minlength=BINS)
    return out / np.maximum(out.sum(1, keepdims=True), 1)


def sparse(x: np.ndarray) -> bytes:
    """The bins of a vector that are not zero, and their values in half precision."""
    at = np.flatnonzero(x)
    return at.astype("<u2").tobytes() + x[at].astype("<f2").tobytes()


def dense(rows: list[bytes]) -> np.ndarray:
    out = np.zeros((len(rows), BINS), np.float32)
    for i, data in enumerate(rows):
        n = len(data) // 4
        out[i, np.frombuffer(data, "<u2", n)] = np.frombuffer(data, "<f2", n, 2 * n)
    return out


# --- machines --------------------------------------------------------------


def linear_machine(x: np.ndarray, y: np.ndarray, c: float = 40.0, steps: int = 300) -> tuple[np.ndarray, float]:
    """Linear support vector machine (squared hinge, y in -1 and 1) by accelerated full gradients."""
    n, d = x.shape
    weight = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum()))
    weight, y = weight.astype(x.dtype), y.astype(x.dtype)
    w, b = np.zeros(d, x.dtype), 0.0
    vw, vb = w.copy(), b
    rate = float(1.0 / (1.0 + 2 * c * (1 + float(weight @ np.einsum("ij,ij->i", x, x)))))
    for t in range(1, steps + 1):
        slack = np.maximum(0, 1 - y * (x @ vw + vb)) * weight * y
        nw = vw - rate * (vw - 2 * c * (x.T @ slack))
        nb = vb + rate * 2 * c * slack.sum()
        k = (t - 1) / (t + 2)
        vw, vb = nw + k * (nw - w), nb + k * (nb - b)
        w, b = nw, nb
    return w.astype(np.float64), float(b)


class Model:
    """Labels, families and the machines: one for each pair of families and of languages within a family."""

    def __init__(self, machines: list[tuple[str, str, str]], families: dict[str, list[str]], weights: np.ndarray, bias: np.ndarray):
        self.machines, self.families, self.weights, self.bias = machines, families, weights, bias

    def values(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Machine outputs of each text, and the number of its features."""
        pool, index, counts = texts_words(texts)
        if not len(pool):
            return np.zeros((len(texts), len(self.machines))), np.zeros(len(texts))
        per_word, sizes = np.zeros((len(pool), len(self.machines))), np.zeros(len(pool), np.int64)
        for bins, owner in word_features(pool):
            sizes += np.bincount(owner, minlength=len(pool))
            for i in range(len(self.machines)):
                per_word[:, i] += np.bincount(owner, weights=self.weights[bins, i], minlength=len(pool))
        total = sums(per_word[index], counts)
        n = sums(sizes[index], counts)
        return total / np.maximum(n, 1)[:, None] + self.bias, n

    def vote(self, values: np.ndarray, scope: str, labels: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Winner of the pairwise votes, then of the summed margins; and its confidence."""
        n = len(values)
        if len(labels) == 1:
            return np.zeros(n, np.int64), np.ones(n)
        points = np.zeros((n, len(labels)))
        least = np.full((n, len(labels)), np.inf)
        for i, (where, a, b) in enumerate(self.machines):
            if where == scope:
                for label, v in ((a, values[:, i]), (b, -values[:, i])):
                    at = labels.index(label)
                    points[:, at] += (v > 0) * 1000.0 + np.tanh(v)
                    least[:, at] = np.minimum(least[:, at], v)
        best = points.argmax(1)
        return best, 1 / (1 + np.exp(-3 * np.clip(least[np.arange(n), best], -20, 20)))

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        values, n = self.values(texts)
        if not self.families:
            return [UNDETERMINED] * len(texts), np.zeros(len(texts))
        names = sorted(self.families)
        family, sure = self.vote(values, "", names)
        found, score = np.full(len(texts), UNDETERMINED, object), np.zeros(len(texts))
        for f, name in enumerate(names):
            mine = np.flatnonzero((family == f) & (n > 0))
            if len(mine):
                at, inner = self.vote(values[mine], name, self.families[name])
                found[mine] = np.array(self.families[name], object)[at]
                score[mine] = sure[mine] * inner
        return found.tolist(), score


def families_of(langs: list[str]) -> dict[str, list[str]]:
    out: dict[str, list[str]] = {}
    for lang in sorted(langs):
        out.setdefault(FAMILY_OF.get(lang, f"only-{lang}"), []).append(lang)
    return out


def machines_of(families: dict[str, list[str]]) -> list[tuple[str, str, str]]:
    """(scope, a, b): every pair of families, then every pair of languages of a family."""
    return [(scope, a, b) for scope, names in [("", sorted(families)), *((f, families[f]) for f in sorted(families))] for a, b in combinations(names, 2)]


def fit(rows: DataFrame, text: str = "text", lang: str = "lang", per_language: int = PER_LANGUAGE) -> Model:
    """Train on labelled rows; at most ``per_language`` different texts of each language, whole texts."""
    from pyspark.sql import Window

    spark = rows.sparkSession
    labelled = rows.select(F.col(lang).alias("lang"), F.xxhash64(text).alias("h"), F.col(text).alias("text")).where("lang is not null and text is not null")
    # Copies share a hash and count once, so no group of copies fills or thins out a language's sample.
    totals = {r.lang: r.n for r in labelled.groupBy("lang").agg(F.approx_count_distinct("h", 0.02).alias("n")).collect()}
    if not totals:
        return Model([], {}, np.zeros((BINS, 0)), np.zeros(0))
    families = families_of(list(totals))
    machines = machines_of(families)
    # Rows by hash below a bound that keeps somewhat more than asked; the exact number is taken among those.
    share = F.create_map(*[x for k, n in totals.items() for x in (F.lit(k), F.lit(min(1.0, (1.5 * per_language + 50) / n)))])
    near = labelled.where((F.pmod(F.col("h"), F.lit(1 << 30)) / float(1 << 30)) < share[F.col("lang")]).groupBy("lang", "h").agg(F.min("text").alias("text"))
    sample = near.withColumn("rank", F.row_number().over(Window.partitionBy("lang").orderBy("h", "text"))).where(F.col("rank") <= per_language)
    if not machines:
        return Model([], families, np.zeros((BINS, 0)), np.zeros(0))
    shape = columns("lang string, rank int, vector binary")

    def vectors(batches):
        for b in batches:
            for part in slices(b, 2, 2 << 20, rows=200):
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1).cast(pa.int32()), pa.array([sparse(v) for v in text_vectors(part.column(2))], pa.binary())], schema=shape)

    made = sample.select("lang", "rank", "text").mapInArrow(lean(vectors), "lang string, rank int, vector binary")
    sides = [(i, x, bool(at == 0), -(-per_language // (1 if scope else len(families[side])))) for i, (scope, *both) in enumerate(machines) for at, side in enumerate(both) for x in ([side] if scope else families[side])]
    dealt = made.join(F.broadcast(spark.createDataFrame(sides, "machine int, lang string, first boolean, most int")), "lang").where("rank <= most").select("machine", "first", "lang", "rank", "vector")

    def train(table: pa.Table) -> pa.Table:
        table = table.sort_by([("lang", "ascending"), ("rank", "ascending")])
        x = dense(table.column("vector").to_pylist())
        scale = (1 / np.sqrt(np.maximum(x.mean(0), 1e-6))).astype(np.float32)  # frequent n-grams weigh less
        x *= scale
        w, bias = linear_machine(x, np.where(table.column("first").to_numpy(zero_copy_only=False), 1.0, -1.0))
        out = pa.table({"machine": pa.array([table.column("machine")[0].as_py()], pa.int32()), "weights": pa.array([(w * scale).astype("<f4").tobytes()], pa.binary()), "bias": [bias]})
        trim()
        return out

    got = {r.machine: r for r in dealt.groupBy("machine").applyInArrow(train, "machine int, weights binary, bias double").collect()}
    weights = np.array([np.frombuffer(got[i].weights, "<f4") for i in range(len(machines))], np.float32)
    return Model(machines, families, weights.T.reshape(BINS, -1), np.array([got[i].bias for i in range(len(machines))]))


def predicted(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """All columns of ``docs`` with ``lang_pred`` and ``score``; older columns of these names are replaced."""
    docs = docs.drop("lang_pred", "score")
    schema = T.StructType([*docs.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    at = docs.columns.index(text)
    names = schema.names

    def run(batches):
        for b in batches:
            for part in slices(b, at, 1 << 20):
                langs, score = model.predict(part.column(at))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(langs, pa.string()), pa.array(score)], names=names)

    return docs.mapInArrow(lean(run), schema)


def held_out(doc_id: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def accepted(docs: DataFrame, model: Model, least: float = 0.0, text: str = "text") -> DataFrame:
    """The rows whose language could be told with a score of ``least`` or more, columns as they were."""
    at = docs.columns.index(text)

    def run(batches):
        for b in batches:
            for part in slices(b, at, 1 << 20):
                langs, score = model.predict(part.column(at))
                yield part.filter(pa.array([x != UNDETERMINED and y >= least for x, y in zip(langs, score.tolist())], pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs.where(~held_out()))
    return predicted(docs.select("doc_id", "text"), model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
