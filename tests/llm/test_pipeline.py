"""The five stages in turn, on given and on awkward rows."""

import sys
import types

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tablemill.llm import simhash
from tablemill.llm.common import lean
from test_operators import EDGE, write

pytest.importorskip("public_tokenizers")


def test_stages_keep_columns(spark, tmp_path):
    docs = spark.read.parquet(f"{write(tmp_path, EDGE)}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns == columns, name
        docs.write.parquet(path := f"{tmp_path}/{name}")
        docs = spark.read.parquet(path)
    last = corpus_pipeline.STAGES[-1][1](spark, docs, str(tmp_path))
    assert last.count() == docs.count()


def test_stages_on_an_empty_table(spark, tmp_path):
    docs = spark.read.parquet(f"{write(tmp_path, [])}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, str(tmp_path)).count() == 0


def test_decisions_take_effect(spark):
    d = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet").cache()
    kept = corpus_pipeline.tell_language(spark, docs, d)
    assert kept.count() >= 0.99 * docs.where(F.col("text").rlike(r"\pL")).count()
    one = corpus_pipeline.drop_near_copies(spark, docs, d)
    assert one.count() == one.select("text").distinct().count()
    lines = corpus_pipeline.drop_repeated_lines(spark, docs, d)
    assert lines.count() == docs.count() and lines.agg(F.sum(F.length("text"))).first()[0] < docs.agg(F.sum(F.length("text"))).first()[0]
    mixed = corpus_pipeline.mix_to_targets(spark, docs, d)
    assert 0 < mixed.select("doc_id").distinct().count() < docs.count()


def test_near_copies_against_all_pairs(spark):
    """Every pair of five-word Jaccard >= 0.8 ends in one group, and groups are made of such pairs only."""
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").orderBy("doc_id").limit(600).select("doc_id", "text").collect()
    base = " ".join(f"w{i}" for i in range(60))
    texts = {r.doc_id: r.text for r in rows} | {9_000_001: base, 9_000_002: base.replace("w30", "x"), 9_000_003: base.replace("w3 ", "y ").replace("w40", "z"), 9_000_004: "w0 w1 w2"}

    def shingles(t):
        w = (t or "").lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}

    sets = {d: shingles(t) for d, t in texts.items()}
    ids, root = sorted(sets), {d: d for d in sets}
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            common = len(sets[a] & sets[b])
            if common >= 0.8 * (len(sets[a]) + len(sets[b]) - common):
                low, high = sorted((root[a], root[b]))
                root = {d: low if r == high else r for d, r in root.items()}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    kept = {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, "").collect()}
    assert kept == set(root.values())
    assert 9_000_001 in kept and 9_000_002 not in kept


def test_candidates_of_near_copies_by_trees():
    """Codes within one bit are found as by all pairs, also where a ball can't be split and over several cells."""
    r = np.random.default_rng(5)
    for bits, n, most in ((12, 3000, 55), (7, 1200, 50), (20, 3000, 60)):
        codes, checks = r.integers(0, 1 << bits, n).astype(np.uint64), r.integers(0, 1 << 63, (n, 2), dtype=np.uint64)
        codes[n // 2 : n // 2 + 60], checks[n // 2 : n // 2 + 50] = codes[7], checks[7]
        near = np.bitwise_count(codes[:, None] ^ codes[None]) <= 1
        near &= np.bitwise_count(checks[:, None] ^ checks[None]).sum(2) <= most
        np.fill_diagonal(near, False)
        want = near.any(1)
        assert 0 < want.sum() and (simhash.accompanied(codes, checks, bits, most) == want).all()
        got = np.zeros(n, bool)
        cells = simhash.routed(simhash.build(np.unique(codes), 100, 1), codes, 1)
        assert len(cells) > 1
        for _, at in cells:
            got[at[simhash.accompanied(codes[at], checks[at], bits, most)]] = True
        assert (got == want).all()


def test_fingerprints_of_sets():
    """Bits counted by words are bits counted one by one, for any room; sets 0.8 alike differ no more than planned."""
    r = np.random.default_rng(6)
    sets = [r.integers(0, 1 << 63, n, dtype=np.uint64) for n in (1, 2, 3, 4, 5, 17, 64, 301, 1500)]
    got = simhash.majorities(sets, 5)
    mults, adds = simhash.permutations(5)
    for s, row in zip(sets, got):
        x = (s[:, None] ^ adds) * mults
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        x ^= x >> np.uint64(32)
        for i in range(64):
            ones = ((x >> np.uint64(i)) & np.uint64(1)).sum(0)
            assert ((2 * ones > len(s)) == ((row >> np.uint64(i)) & np.uint64(1)).astype(bool)).all()
    assert (simhash.majorities(sets, 5, room=40) == got).all()
    x = r.integers(0, 1 << 63, 340, dtype=np.uint64)
    a, b = simhash.majorities([x[:306], np.concatenate([x[:272], x[306:]])], 400)
    assert np.bitwise_count(a ^ b).sum() / (400 * 64) < simhash.bit_chance(0.8)


def test_workers_forget_other_operators():
    """A task drops what other operators remember in its Python worker, and keeps its own."""
    cache = sys.modules.setdefault("tablemill_worker_cache", types.ModuleType("tablemill_worker_cache")).__dict__
    cache |= {"ranks x": 1, "other": 2}
    assert list(lean(lambda batches: batches, keep="ranks")(iter([1]))) == [1] and "other" not in cache and cache["ranks x"] == 1
    assert list(lean(lambda batches: batches)(iter([1]))) == [1] and "ranks x" not in cache
