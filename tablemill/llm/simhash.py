"""SimHash near-deduplication over vantage-point trees.

Fingerprints that differ in at most ``bits`` positions are linked; documents of
one connected component are one group. Equal fingerprints meet in a map-side
combined aggregate first, so a group of copies costs one row however large.

Distinct fingerprints are cut into shards by a vantage-point tree: a node sends
``d <= radius`` inside and the rest outside. Two fingerprints within ``bits`` of
each other can be parted only if the inner one has ``d > radius - bits``
(triangle inequality), so just those inner fingerprints are sent outside as well
and every linked pair meets in some shard. The tree over shards is fitted on a
sample (``PER_LEAF`` fingerprints a shard, by hash order) and every fingerprint is
routed through it. With n fingerprints a shard is meant to hold the larger of
``PER_SHARD`` and four times the root of n, so shards, their size and the sample all
grow as the root. Inside a shard the same rule is applied again, down to leaves
that are compared exactly. A ball too dense to split is not compared pairwise:
fingerprints at distance two or less share one of their one-bit changes, so 65
keys a fingerprint link it in linear work. A shard of ``DENSE`` times its size is
such a ball and is linked by these keys over all tasks, not in one.

Shards return spanning forests, never all pairs; forests are merged by
alternating star contraction with stored rounds.

The pipeline's stage (``near_dedup``) has another rule: texts whose five-word
shingle sets have a Jaccard similarity of 0.8 or more are near copies. Their 64-bit
fingerprints lie up to 11 bits and more apart, where a vantage-point tree no longer
parts anything (a shell that wide holds most fingerprints). A longer fingerprint is
therefore cut into codes of some twenty bits, more for more documents, and each
code has trees of its own, searched within one bit (``NEAR_BITS``). There are so
many codes that fewer than one in ``1 / MISS`` pairs at the least similarity is that
close in none of them. Texts found so are candidates if 128 further bits of their
fingerprints agree as well as those of near copies do; a set of fewer than ``FEW``
shingles is too small for a fingerprint and a candidate in any case.

An exact check follows. The sets of all candidates are cut to prefixes: two sets
that are alike enough share one of their rarest shingles, among the first ``size -
least * size + 1`` of each by frequency. What only one candidate holds is counted
there but pairs with nothing. Every link is confirmed on the exact sets.

Defined results: null and empty texts have fingerprint zero and are linked like
any other; rows with a null document id get a fingerprint but no component and
always stay; repeated rows are one document.
"""

from __future__ import annotations

from collections.abc import Callable
from math import acos, ceil, comb, log, pi

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tablemill.llm.common import columns, forget, free_name, lean, stored, trim, whole
from tablemill.llm.licenses import MISS, permutations, shingle_hashes
from tablemill.llm.pieces import begins, gather

BITS = 2
SHINGLE = 3
SAMPLE = 8192
PER_LEAF = 24
PER_SHARD = 4000
DENSE = 16
LEAF = 384
NEAR_SHINGLE = 5
NEAR = 0.8
NEAR_BITS = 1
FEW = 20
CHECK_BITS = 128
CODE_LEAF = 256
PER_CELL = 1 << 17
CROSSED = 1 << 21


def text_fingerprint(text: bytes, shingle: int = SHINGLE, seed: int = 42) -> int:
    words = text.lower().split()
    if not words:
        return 0
    count = max(1, len(words) - shingle + 1)
    hashes = np.fromiter((xxhash.xxh64_intdigest(b" ".join(words[i : i + shingle]), seed) for i in range(count)), np.uint64, count)
    ones = np.zeros(64, np.int64)
    for at in range(0, count, 1 << 15):
        ones += np.unpackbits(hashes[at : at + (1 << 15)].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > count, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """(doc_id, fp) of every row; fp is the fingerprint's signed 64-bit form."""
    shape = columns("doc_id long, fp long")

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 1000):
                part = b.slice(at, 1000)
                fps = np.fromiter(map(text_fingerprint, whole(part.column(1))), np.uint64, part.num_rows)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fps.view(np.int64))], schema=shape)

    return docs.select(F.col(doc_id).cast("long"), F.col(text)).mapInArrow(lean(run), "doc_id long, fp long")


# --- vantage-point tree ----------------------------------------------------


def distance(fps: np.ndarray, vantage: np.uint64) -> np.ndarray:
    return np.bitwise_count(fps ^ vantage).astype(np.int16)


def choose(fps: np.ndarray, bits: int = BITS) -> tuple[np.uint64, int]:
    """A vantage point and radius near the median that copies the fewest, for links within ``bits``."""
    best = None
    for v in fps[np.linspace(0, len(fps) - 1, min(4, len(fps))).astype(int)]:
        tally = np.bincount(distance(fps, v), minlength=65).cumsum()
        inner = tally[:-1]
        copied = inner - np.concatenate([np.zeros(bits, inner.dtype), inner[:-bits]])
        cost = np.maximum(inner, len(fps) - inner + copied)
        radius = int(cost.argmin())
        if best is None or cost[radius] < best[0]:
            best = (cost[radius], v, radius)
    return best[1], best[2]


def build(sample: np.ndarray, leaf: int, bits: int = BITS) -> list[tuple[int, int, int, int]]:
    """Nodes (vantage, radius, inside, outside); a child below zero is shard -1 - child."""
    nodes: list[list[int]] = []
    shards = 0

    def grow(fps: np.ndarray) -> int:
        nonlocal shards
        if len(fps) > leaf:
            v, radius = choose(fps, bits)
            d = distance(fps, v)
            inside, outside = fps[d <= radius], fps[d > radius - bits]
            if max(len(inside), len(outside)) < 0.9 * len(fps):
                at = len(nodes)
                nodes.append([int(v), radius, 0, 0])
                nodes[at][2] = grow(inside)
                nodes[at][3] = grow(outside)
                return at
        shards += 1
        return -shards

    grow(sample)
    return [tuple(n) for n in nodes]


def routed(nodes: list[tuple[int, int, int, int]], fps: np.ndarray, bits: int = BITS) -> list[tuple[int, np.ndarray]]:
    """Shards, and the places in ``fps`` of what belongs to each or borders on it within ``bits``."""
    todo, out = [(0 if nodes else -1, np.arange(len(fps)))], []
    while todo:
        at, some = todo.pop()
        if not len(some):
            continue
        if at < 0:
            out.append((-1 - at, some))
            continue
        vantage, radius, inside, outside = nodes[at]
        d = distance(fps[some], np.uint64(vantage))
        todo += [(inside, some[d <= radius]), (outside, some[d > radius - bits])]
    return out


def route(nodes: list[tuple[int, int, int, int]], fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(shard, fingerprint) rows: the shard each belongs to and those it borders on."""
    out = [(np.full(len(at), shard, np.int32), fps[at]) for shard, at in routed(nodes, fps)]
    if not out:
        return np.zeros(0, np.int32), np.zeros(0, np.uint64)
    return np.concatenate([x[0] for x in out]), np.concatenate([x[1] for x in out])


def dense_links(fps: np.ndarray) -> np.ndarray:
    """Links of distinct fingerprints through their one-bit changes; rows of two fingerprints."""
    masks = np.concatenate([np.zeros(1, np.uint64), np.uint64(1) << np.arange(64, dtype=np.uint64)])
    passes, found = max(1, len(fps) * 65 // (4 << 20)), []
    for turn in range(passes):
        keys, owners = [], []
        for m in masks:
            k = fps ^ m
            mine = np.arange(len(fps)) if passes == 1 else np.flatnonzero(((k * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)) % np.uint64(passes) == turn)
            keys.append(k[mine])
            owners.append(mine)
        keys, owners = np.concatenate(keys), np.concatenate(owners)
        order = np.argsort(keys, kind="stable")
        keys, owners = keys[order], owners[order]
        new = np.concatenate([[True], keys[1:] != keys[:-1]])
        first = owners[np.flatnonzero(new)[np.cumsum(new) - 1]]
        linked = first != owners
        found.append(np.unique(np.stack([first[linked], owners[linked]], 1), axis=0))
    every = np.concatenate(found)
    return np.stack([fps[every[:, 0]], fps[every[:, 1]]], 1)


def links(fps: np.ndarray, leaf: int = LEAF) -> np.ndarray:
    """Enough exact links among distinct fingerprints to hold all components together."""
    todo, out = [fps], []
    while todo:
        some = todo.pop()
        if len(some) < 2:
            continue
        if len(some) <= leaf:
            a, b = np.nonzero(np.triu(np.bitwise_count(some[:, None] ^ some[None, :]) <= BITS, 1))
            if len(a):
                out.append(np.stack([some[a], some[b]], 1))
            continue
        v, radius = choose(some)
        d = distance(some, v)
        inside, outside = some[d <= radius], some[d > radius - BITS]
        if max(len(inside), len(outside)) >= 0.9 * len(some) or len(inside) + len(outside) > 1.6 * len(some):
            out.append(dense_links(some))
        else:
            todo += [inside, outside]
    return np.concatenate(out) if out else np.zeros((0, 2), np.uint64)


def forest(pairs: np.ndarray) -> np.ndarray:
    """(member, root) rows: the smallest fingerprint of each local component is its root."""
    if not len(pairs):
        return pairs
    nodes, flat = np.unique(pairs, return_inverse=True)
    flat = flat.reshape(-1, 2)
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[flat[:, 0]], label[flat[:, 1]])
        new = label.copy()
        np.minimum.at(new, flat[:, 0], low)
        np.minimum.at(new, flat[:, 1], low)
        np.minimum.at(new, label[flat[:, 0]], low)
        np.minimum.at(new, label[flat[:, 1]], low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    member = label != np.arange(len(nodes))
    return np.stack([nodes[member], nodes[label[member]]], 1)


def shard_links(distinct: DataFrame, sample: int = SAMPLE, per_shard: int | None = None, dense: int = DENSE) -> DataFrame:
    """(a, b): spanning links between distinct fingerprints of the column ``fp``."""
    n = distinct.count()
    per_shard = per_shard or max(PER_SHARD, int(4 * n**0.5))
    seen = distinct.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(max(sample, PER_LEAF * (n // per_shard))).collect()
    some = np.array([r.fp for r in seen], np.int64).view(np.uint64)
    nodes = build(some, max(PER_LEAF, int(len(some) * per_shard / max(n, 1))))
    shape = columns("shard int, fp long")

    def send(batches):
        for b in batches:
            shard, fp = route(nodes, b.column(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64))
            yield pa.RecordBatch.from_arrays([pa.array(shard), pa.array(fp.view(np.int64))], schema=shape)

    def solve(table):
        fps = np.unique(table.column("fp").to_numpy().astype(np.int64).view(np.uint64))
        tree = forest(links(fps)).view(np.int64).reshape(-1, 2)
        return pa.table({"a": tree[:, 0], "b": tree[:, 1]})

    dealt = stored(distinct.select("fp").mapInArrow(lean(send), "shard int, fp long"), "shards")
    balls = dealt.groupBy("shard").agg(F.count("*").alias("n")).where(F.col("n") > dense * per_shard).select("shard")
    if not balls.take(1):
        return dealt.groupBy("shard").applyInArrow(solve, "a long, b long")
    # There are no more shards than ``build`` has leaves, so their numbers can travel.
    rest = dealt.join(F.broadcast(balls), "shard", "left_anti").groupBy("shard").applyInArrow(solve, "a long, b long")
    return rest.unionByName(changed_links(dealt.join(F.broadcast(balls), "shard", "left_semi").select("fp").distinct()))


def changed_links(fps: DataFrame) -> DataFrame:
    """Links of fingerprints through their one-bit changes, to the least that shares a key; as ``dense_links``, over all tasks."""
    masks = F.array(F.lit(0).cast("long"), *[F.lit(1 << i).cast("long") for i in range(63)], F.lit(-(1 << 63)).cast("long"))
    keyed = fps.select("fp", F.explode(F.transform(masks, lambda m: F.col("fp").bitwiseXOR(m))).alias("key"))
    least = keyed.groupBy("key").agg(F.min("fp").alias("a"), F.max("fp").alias("top")).where("a < top").select("key", "a")
    return keyed.join(least, "key").where("a < fp").select("a", F.col("fp").alias("b")).distinct()


# --- components ------------------------------------------------------------


def star_components(edges: DataFrame) -> DataFrame:
    """(node, root) of all linked nodes, by alternating large and small stars; roots are the smallest nodes."""

    def round_of(e: DataFrame) -> DataFrame:
        both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        return small.where("u <> v").distinct()

    def mark(e: DataFrame):
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())

    now = stored(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "stars")
    before = mark(now)
    while before[0]:
        now, last = stored(round_of(now), "stars"), now
        forget(last)
        after = mark(now)
        if after == before:
            break
        before = after
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))


def components(prints: DataFrame, sample: int = SAMPLE, per_shard: int | None = None, dense: int = DENSE) -> DataFrame:
    """doc_id, fp, component_id of fingerprinted documents (a stored table of doc_id, fp)."""
    return joined(prints, lambda distinct: shard_links(distinct, sample, per_shard, dense))


def joined(prints: DataFrame, linked_by: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """doc_id, fp, component_id, given what links the distinct fingerprints (fp, low, high)."""
    distinct = stored(prints.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high")), "distinct-prints")
    roots = star_components(linked_by(distinct))
    linked = roots.select(F.col("node").alias("fp"), "root").unionByName(roots.select(F.col("root").alias("fp"), "root").distinct())
    of = distinct.join(linked, "fp", "left").where("root is not null or low < high").withColumn("root", F.coalesce("root", "fp"))
    least = of.groupBy("root").agg(F.min("low").alias("component"))
    known = of.join(least, "root").select("fp", "component")
    return prints.join(known, "fp", "left").select("doc_id", "fp", F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component_id"))


def groups(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    return components(stored(fingerprints(docs, text, doc_id), "prints"))


def near_dedup(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = NEAR_SHINGLE, least: float = NEAR) -> DataFrame:
    """One document of each group of near copies stays: the smallest id. Other columns pass through."""
    name = free_name(docs, "_leaves")
    leaves = near_groups(docs, text, doc_id, shingle, least).where("component_id < doc_id").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(leaves, F.col(doc_id).cast("long") == F.col(name), "left_anti")


# --- near copies of the pipeline -------------------------------------------


def shingle_set(text: str | None, shingle: int = NEAR_SHINGLE) -> np.ndarray:
    """Sorted hashes of the distinct runs of ``shingle`` words (all words of a shorter text); no word gives none."""
    keys = np.array([xxhash.xxh64_intdigest(w) for w in (text or "").lower().split()], np.uint64)
    return np.unique(shingle_hashes(keys, min(shingle, len(keys)))) if len(keys) else keys


def bit_chance(least: float, fewest: int = FEW) -> float:
    """The most likely a bit of two fingerprints differs, of sets that are ``least`` alike and have ``fewest`` shingles or more.

    For large sets it is the angle between them over a half turn; small ones, where
    ties are not rare, come to somewhat more (0.158 for 0.8 and 20, by enumeration).
    """
    return acos(2 * least / (1 + least)) / pi * (1 + 1 / fewest)


def code_plan(n: int, least: float, miss: float = MISS) -> tuple[int, int, int]:
    """(bits of a code, number of codes, most of the check's bits that may differ) for ``n`` documents.

    A code is long enough that a document meets about four strangers in its ball; the
    codes and the check together miss less than ``miss`` of the pairs.
    """
    p, bits = bit_chance(least), 12
    while bits < 60 and n * (bits + 1) > 4 << bits:
        bits += 1
    near = sum(comb(bits, k) * p**k * (1 - p) ** (bits - k) for k in range(NEAR_BITS + 1))
    codes = 1 if near >= 1 else ceil(log(miss / 2) / log(1 - near))
    tail, most = 1.0, -1
    while tail > miss / 2:
        most += 1
        tail -= comb(CHECK_BITS, most) * p**most * (1 - p) ** (CHECK_BITS - most)
    return bits, codes, most


def words_of(bits: int, codes: int) -> int:
    """64-bit words of a fingerprint: the check's, then those that hold as many whole codes as fit."""
    return CHECK_BITS // 64 + -(-codes // (64 // bits))


def majorities(sets: list[np.ndarray], words: int, room: int = 1 << 16) -> np.ndarray:
    """SimHash fingerprints of ``words`` 64-bit words, a row a set: a bit is 1 if set in over half the hashes.

    Bits are counted 64 at a time: hashes are added pairwise as binary numbers whose
    digits are words. Sets of a like size are counted together; empty sets are not allowed.
    """
    size = np.fromiter(map(len, sets), np.int64, len(sets))
    out = np.empty((len(sets), words), np.uint64)
    mults, adds = permutations(words)
    order, at = np.argsort(size, kind="stable"), 0
    while at < len(order):
        fits = int(np.searchsorted(size[order], size[order[at]] * 5 // 4 + 4, side="right"))
        widest = int(size[order[fits - 1]])
        end = min(fits, at + max(1, room // (widest * words)))
        mine = order[at:end]
        n = size[mine]
        hashes = np.zeros((len(mine), int(n.max()), 1), np.uint64)
        real = np.arange(hashes.shape[1]) < n[:, None]
        hashes[real, 0] = np.concatenate([sets[i] for i in mine])
        step = max(1, room // hashes.size)
        for w in range(0, words, step):
            x = (hashes ^ adds[w : w + step]) * mults[w : w + step]
            x ^= x >> np.uint64(32)
            x *= np.uint64(0xD6E8FEB86659FD93)
            x ^= x >> np.uint64(32)
            x[~real] = 0
            digits = [x]
            while digits[0].shape[1] > 1:
                if digits[0].shape[1] % 2:
                    digits = [np.concatenate([d, np.zeros_like(d[:, :1])], 1) for d in digits]
                carry, total = None, []
                for a, b in ((d[:, ::2], d[:, 1::2]) for d in digits):
                    half = a ^ b
                    total.append(half if carry is None else half ^ carry)
                    carry = a & b if carry is None else (a & b) | (carry & half)
                digits = [*total, carry]
            above, same = np.zeros_like(digits[0][:, 0]), np.full_like(digits[0][:, 0], ~np.uint64(0))
            for k in reversed(range(len(digits))):
                digit, of_half = digits[k][:, 0], (-((n // 2 >> k) & 1)).astype(np.int64).view(np.uint64)[:, None]
                above |= same & digit & ~of_half
                same &= ~(digit ^ of_half)
            out[mine, w : w + step] = above
        at = end
    return out


def code_of(prints: np.ndarray, number: int, bits: int) -> np.ndarray:
    """The code of that number of each fingerprint (rows of words)."""
    per = 64 // bits
    return (prints[:, CHECK_BITS // 64 + number // per] >> np.uint64(number % per * bits)) & np.uint64((1 << bits) - 1)


def close_codes(codes: np.ndarray, bits: int, leaf: int = CODE_LEAF) -> np.ndarray:
    """All pairs of distinct codes within one bit, as rows of two; a pair may come more than once."""
    todo, out = [codes.astype(np.uint32) if bits <= 32 else codes], []
    while todo:
        some = todo.pop()
        if len(some) < 2:
            continue
        if len(some) <= leaf:
            a, b = divmod(np.flatnonzero(np.bitwise_count(some[:, None] ^ some[None, :]) == NEAR_BITS), len(some))
            if len(a):
                out.append(np.stack([some[a], some[b]], 1)[a < b])
            continue
        # One vantage point is as good as another among codes without order; only its radius is chosen.
        d = np.bitwise_count(some ^ some[len(some) // 2])
        tally = np.bincount(d, minlength=bits + 1).cumsum()
        radius = int(np.maximum(tally[NEAR_BITS:-1], len(some) - tally[: -1 - NEAR_BITS]).argmin()) + NEAR_BITS
        inside, outside = some[d <= radius], some[d + NEAR_BITS > radius]
        if max(len(inside), len(outside)) >= 0.9 * len(some) or len(inside) + len(outside) > 1.6 * len(some):
            # A ball too dense to split: each code's one-bit changes are looked up.
            some = np.sort(some)
            for i in range(bits):
                other = some ^ some.dtype.type(1 << i)
                found = (some[np.minimum(np.searchsorted(some, other), len(some) - 1)] == other) & (some < other)
                out.append(np.stack([some[found], other[found]], 1))
        else:
            todo += [inside, outside]
    return np.concatenate(out).astype(np.uint64) if out else np.zeros((0, 2), np.uint64)


def accompanied(codes: np.ndarray, checks: np.ndarray, bits: int, most: int) -> np.ndarray:
    """Which rows have another whose code is within one bit and whose check within ``most``.

    Only that is asked, so a row that has a partner needs no other: a group of copies
    is marked by one of them, and codes are crossed for rows that are still alone.
    """
    order = np.argsort(codes, kind="stable")
    codes, checks = codes[order], checks[order]
    known, first, count = np.unique(codes, return_index=True, return_counts=True)
    marked, asked = np.zeros(len(codes), bool), np.zeros(len(codes), bool)

    def alike(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.bitwise_count(checks[a] ^ checks[b]).sum(1, dtype=np.int64) <= most

    waiting = np.flatnonzero(count > 1)
    while len(waiting):
        rows = gather(np.arange(len(codes)), first[waiting], count[waiting])
        free = np.where(marked[rows] | asked[rows], len(codes), rows)
        pivot = np.minimum.reduceat(free, begins(count[waiting]))
        left = pivot < len(codes)
        waiting, pivot = waiting[left], pivot[left]
        if not len(waiting):
            break
        rows, against = gather(np.arange(len(codes)), first[waiting], count[waiting]), np.repeat(pivot, count[waiting])
        hit = (rows != against) & alike(rows, against)
        marked[rows[hit]] = marked[against[hit]] = asked[pivot] = True
    pairs = np.searchsorted(known, close_codes(known, bits))
    both = np.concatenate([pairs, pairs[:, ::-1]])
    alone = np.add.reduceat(~marked, first) if len(first) else first
    both = both[alone[both[:, 0]] > 0]
    lonely = np.flatnonzero(~marked)
    starts = np.searchsorted(lonely, first)
    work = np.cumsum(alone[both[:, 0]])
    at = 0
    while at < len(both):
        end = max(at + 1, int(np.searchsorted(work, (work[at - 1] if at else 0) + (CROSSED >> 4), side="right")))
        a, b = both[at:end].T
        mine = gather(lonely, starts[a], alone[a])
        of = np.repeat(b, alone[a])
        some = np.cumsum(count[of])
        i = 0
        while i < len(mine):
            j = max(i + 1, int(np.searchsorted(some, (some[i - 1] if i else 0) + CROSSED, side="right")))
            x, y = np.repeat(mine[i:j], count[of[i:j]]), gather(np.arange(len(codes)), first[of[i:j]], count[of[i:j]])
            hit = alike(x, y)
            marked[x[hit]] = marked[y[hit]] = True
            i = j
        at = end
    out = np.empty(len(codes), bool)
    out[order] = marked
    return out


def shingled(docs: DataFrame, text: str, doc_id: str, shingle: int, words: int) -> DataFrame:
    """(doc_id, fp, code, few) of every row: fp stands for the set of shingles, code is its SimHash fingerprint of
    ``words`` words unless the set is empty, and few says that the set may have a partner too small for one."""
    returns = "doc_id long, fp long, code binary, few boolean"
    shape = columns(returns)

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 200):
                part = b.slice(at, 200)
                sets = [shingle_set(t, shingle) for t in part.column(1).to_pylist()]
                some = [s for s in sets if len(s)]
                codes = iter(majorities(some, words)) if some else iter(())
                fps = np.array([xxhash.xxh64_intdigest(s.tobytes()) if len(s) else 0 for s in sets], np.uint64)
                code = pa.array([next(codes).astype("<u8").tobytes() if len(s) else None for s in sets], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fps.view(np.int64)), code, pa.array([0 < len(s) < 2 * FEW for s in sets])], schema=shape)

    return docs.select(F.col(doc_id).cast("long"), F.col(text).cast("string")).mapInArrow(lean(run), returns)


def shingle_sets(docs: DataFrame, text: str, doc_id: str, shingle: int) -> DataFrame:
    """(doc_id, fp, hashes) of every row: the set of shingles and what stands for it."""
    shape = columns("doc_id long, fp long, hashes array<long>")

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 200):
                part = b.slice(at, 200)
                sets = [shingle_set(t, shingle) for t in part.column(1).to_pylist()]
                fps = np.array([xxhash.xxh64_intdigest(s.tobytes()) if len(s) else 0 for s in sets], np.uint64)
                ends = np.cumsum([0, *map(len, sets)]).astype(np.int32)
                hashes = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0, np.uint64), *sets]).view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fps.view(np.int64)), hashes], schema=shape)

    return docs.select(F.col(doc_id).cast("long"), F.col(text).cast("string")).mapInArrow(lean(run), "doc_id long, fp long, hashes array<long>")


def near_candidates(prints: DataFrame, plan: tuple[int, int, int], per_cell: int | None = None) -> DataFrame:
    """(fp) of the sets that may have a near copy: those with another in reach in a vantage-point tree of some code, and those of few shingles.

    A cell is a shard of one code's tree. A task of the first step packs what it
    sends to a cell into one row. Cells grow as the root of the sets, and so does the
    sample that the trees over cells are fitted on.
    """
    bits, codes, most = plan
    coded = stored(prints.where("doc_id is not null and code is not null").groupBy("fp").agg(F.min("code").alias("code"), F.max("few").alias("few")), "near-codes")
    n = coded.count()
    per_cell = per_cell or max(PER_CELL, int(64 * n**0.5))
    trees: list[list[tuple[int, int, int, int]]] = [[] for _ in range(codes)]
    if n > per_cell:
        seen = coded.orderBy(F.xxhash64("fp"), "fp").limit(PER_LEAF * 4 * -(-n // per_cell)).select("code").collect()
        some = np.array([np.frombuffer(r.code, "<u8") for r in seen])
        trees = [build(np.unique(code_of(some, c, bits)), max(PER_LEAF, int(len(some) * per_cell / n)), NEAR_BITS) for c in range(codes)]
    shape = columns("number int, shard int, codes binary, checks binary")

    def send(batches):
        for b in batches:
            if not b.num_rows:
                continue
            every = np.frombuffer(b"".join(b.column(0).to_pylist()), "<u8").reshape(b.num_rows, -1)
            checks = np.ascontiguousarray(every[:, : CHECK_BITS // 64])
            for c, nodes in enumerate(trees):
                mine = code_of(every, c, bits)
                kind = "<u4" if bits <= 32 else "<u8"
                rows = [(shard, mine[at].astype(kind).tobytes(), checks[at].tobytes()) for shard, at in routed(nodes, mine, NEAR_BITS)]
                yield pa.RecordBatch.from_arrays([pa.array([c] * len(rows), pa.int32()), pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.binary())], schema=shape)

    def search(table):
        mine = np.frombuffer(b"".join(table.column("codes").to_pylist()), "<u4" if bits <= 32 else "<u8").astype(np.uint64)
        checks = np.frombuffer(b"".join(table.column("checks").to_pylist()), "<u8").reshape(len(mine), -1)
        found = checks[accompanied(mine, checks, bits, most)]
        out = pa.table({"check": pa.array([x.tobytes() for x in found], pa.binary())})
        trim()
        return out

    sent = coded.select("code").mapInArrow(lean(send), "number int, shard int, codes binary, checks binary")
    # Sets of one check have all their near copies in common, so the check can stand for them.
    found = stored(sent.groupBy("number", "shard").applyInArrow(search, "check binary").distinct(), "near-found")
    check = F.substring("code", 1, CHECK_BITS // 8)
    reached = coded.withColumn("check", check).join(found, "check", "left_semi").select("fp")
    return reached.unionByName(coded.where("few").select("fp")).distinct()


def near_links(candidates: DataFrame, distinct: DataFrame, least: float, sets_of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(a, b): links between sets that are ``least`` alike, enough to hold all components together.

    Only the sets of ``candidates`` are made in full. A bucket is the candidates that
    have one shingle in their prefixes. Its member with the fewest shingles of its own
    is compared with all others first; only a bucket that still holds several
    components is compared across them.
    """
    wanted = distinct.join(candidates, "fp", "left_semi").select(F.col("low").alias("doc_id"))
    sets = stored(sets_of(wanted), "near-sets")
    members = stored(prefixes(sets, least), "near-prefixes")

    def confirmed(some: DataFrame) -> DataFrame:
        both = some.join(sets.select(F.col("fp").alias("a"), F.col("hashes").alias("x")), "a").join(sets.select(F.col("fp").alias("b"), F.col("hashes").alias("y")), "b")
        common = F.size(F.array_intersect("x", "y"))
        return stored(both.select("a", "b", common.alias("common"), (F.size("x") + F.size("y")).alias("sizes")).where(F.col("common") >= F.lit(least) * (F.col("sizes") - F.col("common"))).select("a", "b"), "near-links")

    def fitting(x: str, y: str) -> Column:
        """Whether two members can be alike enough, by their sizes, by the shingles that others have too, and
        because the rarest shingle they share leaves neither of them too few."""
        of = lambda m, c: F.col(f"{m}.{c}")
        need = F.ceil(F.lit(least / (1 + least)) * (of(x, "size") + of(y, "size")) - 1e-6)
        return (F.least(of(x, "size") - of(x, "place"), of(y, "size") - of(y, "place")) >= need) & (F.least(of(x, "size") - of(x, "own"), of(y, "size") - of(y, "own")) >= need)

    pivots = members.groupBy("key").agg(F.min(F.struct("own", "fp", "size", "place")).alias("p"), F.count("*").alias("n")).where("n > 1").select("key", "p.*")
    pairs = members.alias("m").join(pivots.alias("p"), (F.col("m.key") == F.col("p.key")) & (F.col("m.fp") != F.col("p.fp")) & fitting("m", "p"))
    first = confirmed(pairs.select(F.least("m.fp", "p.fp").alias("a"), F.greatest("m.fp", "p.fp").alias("b")).distinct())
    roots = star_components(first)
    named = members.join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    several = named.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("top")).where("low < top").select("key")
    left = stored(named.join(several, "key", "left_semi"), "near-left")
    across = left.alias("m").join(left.alias("p"), (F.col("m.key") == F.col("p.key")) & (F.col("m.fp") < F.col("p.fp")) & (F.col("m.root") != F.col("p.root")) & fitting("m", "p"))
    return first.unionByName(confirmed(across.select(F.col("m.fp").alias("a"), F.col("p.fp").alias("b")).distinct()))


def prefixes(sets: DataFrame, least: float) -> DataFrame:
    """(key, fp, size, own, place): the rarest shingles of each set that another of ``sets`` has, as far as its prefix reaches.

    ``own`` counts the shingles that no other set has, ``place`` all that come before the key.
    """
    each = sets.select("fp", F.size("hashes").alias("size"), F.explode("hashes").alias("key"))
    shared = each.groupBy("key").agg(F.count("*").alias("times")).where("times > 1")
    ranked = each.join(shared, "key").groupBy("fp", "size").agg(F.sort_array(F.collect_list(F.struct("times", "key"))).alias("shared"))
    own = F.col("size") - F.size("shared")
    reach = F.col("size") - F.ceil(F.lit(least) * F.col("size") - 1e-6) + 1 - own
    placed = ranked.select("fp", "size", own.alias("own"), F.posexplode(F.slice("shared", F.lit(1), F.greatest(F.lit(0), reach).cast("int"))).alias("at", "s"))
    return placed.select(F.col("s.key").alias("key"), "fp", "size", "own", (F.col("own") + F.col("at")).alias("place"))


def near_groups(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", shingle: int = NEAR_SHINGLE, least: float = NEAR) -> DataFrame:
    """doc_id, fp, component_id: components of documents whose shingle sets have a Jaccard similarity of ``least`` or more."""
    plan = code_plan(docs.count(), least)
    prints = stored(shingled(docs, text, doc_id, shingle, words_of(*plan[:2])), "shingles")

    def sets_of(wanted: DataFrame) -> DataFrame:
        """(fp, hashes) of documents (doc_id), one row a set; a further set under a repeated id does no harm."""
        rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).join(wanted, "doc_id", "left_semi")
        return shingle_sets(rows, "text", "doc_id", shingle).select("fp", "hashes").dropDuplicates(["fp"])

    return joined(prints, lambda distinct: near_links(near_candidates(prints, plan), distinct, least, sets_of))


def op8_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
