"""The ten operators against brute force, round trips and edge cases."""

import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from tablemill.llm import bpe, language, licenses, line_dedup, pieces, raking, rans, registry, scaled_sketch, simhash, telephony, wordpiece

P = pytest.importorskip("public_tokenizers")

WORDS = "the of and to in is that for on with as was at by be this are from or an".split()
LONG = " ".join(WORDS[i % 20] + str(i % 97) for i in range(30_000))
EDGE = [
    (1, "one two three four five six seven", "en", "a"),
    (2, "one two three four five six seven", "en", "a"),
    (3, None, None, None),
    (4, "", "fr", ""),
    (5, "   \n\t\n", None, "b"),
    (6, LONG, "en", "a"),
    (7, LONG + " x", "en", "a"),
    (8, "A Shared Line here\nown words stay\nA Shared Line here", "en", "b"),
    (9, "own words differ\n  a shared line HERE \t", "en", None),
    (10, "Ünïcödé ßtraße 日本語 données été\nReleased under the MIT License.", "fr", "b"),
    (11, "12345 !!! ...", None, "b"),
    (None, "row without an id, a shared line here\nA Shared Line here", "en", "a"),
    (1, "one two three four five six seven", "en", "a"),
    (13, "".join("abcdefghijklmnopqrstuvwxyz"[(i * i + i // 7) % 26] for i in range(60_000)), "de", "b"),  # no break at all
    (14, "=" * 5_000 + "ab" * 5_000, None, None),
    (12, "don't  stop;\r\nit's a 'test' <|endoftext|> x" + "y" * 700, "en", "a"),
]


def write(folder, rows):
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("lang", pa.string()), ("source", pa.string()), ("n_chars", pa.int64())] + [(c, pa.int64()) for c in ("k", "fp", "shard", "part", "range", "score", "lang_pred", "topic", "_gone", "_leaves", "ids", "sketch", "ratio", "_cell_ratio")])
    cols = list(zip(*rows)) if rows else [()] * 4
    data = [*cols, [len(x or "") for x in cols[1]]] + [[7] * len(rows)] * 14
    pq.write_table(pa.Table.from_arrays([pa.array(c, t) for c, t in zip(data, schema.types)], schema=schema), f"{folder}/documents.parquet")
    return str(folder)


@pytest.fixture(scope="module")
def edge(tmp_path_factory):
    return write(tmp_path_factory.mktemp("edge"), EDGE)


@pytest.fixture(scope="module")
def none(tmp_path_factory):
    return write(tmp_path_factory.mktemp("none"), [])


@pytest.mark.parametrize("name", registry.QUERIES)
def test_empty_table(spark, none, name):
    assert registry.QUERIES[name](spark, none).collect() == []


@pytest.mark.parametrize("name", [n for n in registry.QUERIES if not n.startswith("op3")])
def test_every_row_is_answered(spark, edge, name):
    rows = registry.QUERIES[name](spark, edge).collect()
    assert sorted((r.doc_id is None, r.doc_id) for r in rows) == sorted((e[0] is None, e[0]) for e in EDGE)


# --- 1 -----------------------------------------------------------------------


def brute_lines(rows):
    def key(x):
        k = x.strip(" \t\n\x0b\x0c\r")
        k = "".join(c.lower() if "A" <= c <= "Z" else c for c in k)
        return k if len(k) >= 10 else None

    at = {}
    for i, t, *_ in rows:
        if i is not None:
            for x in (t or "").split("\n"):
                if k := key(x):
                    at.setdefault(k, set()).add(i)
    out = []
    for i, t, *_ in rows:
        ls = (t or "").split("\n")
        kept = [x for x in ls if i is None or not (k := key(x)) or len(at[k]) < 2 or i == min(at[k])]
        out.append((i, len(ls), len(ls) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return out


def test_line_dedup(spark, edge):
    got = [tuple(r)[:4] for r in registry.QUERIES["op1_line_dedup"](spark, edge).collect()]
    assert sorted(got, key=str) == sorted(brute_lines(EDGE), key=str)


def drops(rows):
    return {(r.doc_id, frozenset(r.gone[i : i + 32] for i in range(0, len(r.gone), 32))) for r in rows}


def test_line_dedup_in_any_increments(spark, small):
    """One batch or several, few shards or many that have to be dealt anew: the same lines go."""
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    one = drops(line_dedup.dropped_lines(docs, batches=1).collect())
    assert one and one == drops(line_dedup.dropped_lines(docs, batches=3, per_shard=3).collect())


def test_cuckoo_filter():
    rng = np.random.default_rng(3)
    keys, other = rng.integers(0, 1 << 63, (20_000, 2)).astype(np.uint64), rng.integers(0, 1 << 63, (20_000, 2)).astype(np.uint64)
    f = line_dedup.CuckooFilter.sized(len(keys))
    f.add(keys)
    f = line_dedup.CuckooFilter.load(f.dump())
    assert f.has(keys).all() and f.has(other).mean() < 0.001
    f.remove(keys[:10_000])
    assert f.has(keys[10_000:]).all() and f.has(keys[:10_000]).mean() < 0.001
    tiny = line_dedup.CuckooFilter(1)  # more than fits goes to the stash
    tiny.add(keys[:9])
    assert tiny.has(keys[:9]).all() and len(tiny.stash) == 5


def test_shard_on_both_sides(spark):
    import os

    keys = [os.urandom(16) for _ in range(200)]
    rows = spark.createDataFrame([(k,) for k in keys], "k binary").withColumn("s", line_dedup.shard_column(7)).collect()
    assert [r.s for r in rows] == line_dedup.shard_of(line_dedup.digest_words([bytes(r.k) for r in rows]), 7).tolist()


def state(index):
    """References, counts, and what the filters say of every line ever counted."""
    counts = {bytes(r.k): r.n for r in index.counted().collect()}
    ever = [bytes(r.k) for r in index._all("counts", line_dedup.COUNTS).select("k").distinct().collect()]
    held = {r.shard: line_dedup.CuckooFilter.load(bytes(r.filter)) for r in index.filters().collect()}
    seen = {k for k in ever if (s := int(line_dedup.shard_of(line_dedup.digest_words([k]), index.now["shards"])[0])) in held and held[s].has(line_dedup.digest_words([k]))[0]}
    return {(bytes(r.k), r.doc_id) for r in index.refs().collect()}, counts, seen


def test_index_is_reversible(spark):
    frame = lambda rows: spark.createDataFrame(rows, "doc_id long, text string")
    ids = lambda *n: spark.createDataFrame([(i,) for i in n], "doc_id long")
    index = line_dedup.LineIndex(spark)
    assert index.insert(frame([(1, "the first line of one\nshared by everyone"), (2, "the second line")])).count() == 0
    before = state(index)
    assert index.insert(frame([(3, "Shared by everyone\na third line"), (4, "nothing in common")])).count() == 1
    assert [(r.keeper, r.n_refs) for r in index.repeats().collect()] == [(1, 2)]
    again = line_dedup.LineIndex(spark, index.path)  # opened by its path only
    assert again.now == index.now and state(again) == state(index)
    again.delete(ids(3, 4))
    assert state(again) == before and again.repeats().count() == 0
    assert again.insert(frame([(5, "a third line"), (3, "a third line")])).count() == 0  # gone from filter and table, and back again
    again.compact()
    assert line_dedup.LineIndex(spark, index.path).repeats().count() == 1
    again.delete(ids(1))
    assert again.insert(frame([(6, "the second line")])).count() == 1
    again.destroy()


def test_index_state_after_a_batch_leaves(spark, small):
    """All documents in, a batch more, the batch out: references, counts and filters are as before."""
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    index = line_dedup.LineIndex(spark, per_shard=10)
    index.insert(line_dedup.increment(docs, 0, 2))
    before, shards = state(index), index.now["shards"]
    index.insert(line_dedup.increment(docs, 1, 2))
    assert shards > 32 and state(index) != before
    index.delete(line_dedup.increment(docs, 1, 2).select("doc_id"))
    after = state(index)
    assert after[:2] == before[:2] and after[2] >= before[2] and len(after[2]) <= len(before[2]) + 2
    index.destroy()


# --- 2 -----------------------------------------------------------------------


def shingle_set(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def jaccard(a, b):
    return len(a & b) / len(a | b) if a | b else 1.0


def test_scaled_sketch(spark, small):
    rows = {r.doc_id: r for r in registry.QUERIES["op2_scaled_sketch"](spark, small).collect()}
    docs = sorted(pq.read_table(f"{small}/documents.parquet").to_pylist(), key=lambda d: d["doc_id"])
    errors = []
    for i, d in enumerate(docs):
        t, after, r = d["text"], docs[(i + 1) % len(docs)]["text"], rows[d["doc_id"]]
        edited = t[: len(t) - len(t) // 2] + after[: len(t) // 2]
        assert (r.n_chars, r.edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        errors.append(r.near_edited - jaccard(shingle_set(t), shingle_set(edited)))
        assert 0 <= r.near_next <= 1
    assert np.sqrt(np.mean(np.square(errors))) < 0.06
    same = {}
    for d in docs:
        assert same.setdefault(d["text"], rows[d["doc_id"]].fingerprint) == rows[d["doc_id"]].fingerprint


def test_sketch_edge_values(spark, edge):
    """Edited texts, their digests and likenesses on awkward rows; short texts are exact."""
    rows = sorted(((e[0], e[1] or "") for e in EDGE), key=lambda e: (e[0] is not None, e[0] or 0))
    got = registry.QUERIES["op2_scaled_sketch"](spark, edge).collect()
    ids = [r[0] for r in rows]
    for r in got:
        if ids.count(r.doc_id) > 1 or r.doc_id is None:
            continue
        at = ids.index(r.doc_id)
        text, after = rows[at][1], rows[(at + 1) % len(rows)][1]
        edited = text[: len(text) - len(text) // 2] + after[: len(text) // 2]
        assert (r.n_chars, r.edited_sha256) == (len(text), hashlib.sha256(edited.encode()).hexdigest())
        if max(len(text), len(edited), len(after)) < 400:
            assert abs(r.near_edited - jaccard(shingle_set(text), shingle_set(edited))) < 1e-9
            assert abs(r.near_next - jaccard(shingle_set(text), shingle_set(after))) < 1e-9


def test_sketch_merges_and_contains(spark):
    a, b = " ".join(f"a{i}" for i in range(3000)), " ".join(f"b{i}" for i in range(300))
    s = scaled_sketch.sketch
    row = spark.range(1).select(s(F.lit(a)).alias("a"), s(F.lit(b)).alias("b"), s(F.lit(a + " " + b)).alias("ab"), s(F.lit("")).alias("none"))
    got = row.select(scaled_sketch.containment(F.col("b"), F.col("ab")).alias("c"), scaled_sketch.likeness(F.col("none"), F.col("none")).alias("e"), scaled_sketch.likeness(F.col("none"), F.col("a")).alias("z"), scaled_sketch.merged(F.col("a"), F.col("b")).alias("m"), "ab").first()
    assert got.c > 0.9 and got.e == 1 and got.z == 0
    assert len(set(got.m) & set(got.ab)) > 0.9 * len(got.m)


def test_next_row_over_ranges(spark):
    docs = spark.range(50).select((F.col("id") * 3 + 1).alias("doc_id"), F.concat(F.lit("t"), "id").alias("text"))
    for per_range, most in ((7, 1000), (1, 1000), (1, 5), (1000, 1000)):
        got = {r.doc_id: r.next_text for r in scaled_sketch.with_next(docs, ["text"], per_range=per_range, most=most).collect()}
        assert got == {i * 3 + 1: f"t{(i + 1) % 50}" for i in range(50)}


def test_next_row_of_equal_ids_and_nulls(spark):
    """Equal and missing ids may fill several ranges; each row still has one follower, and all but one are followed once."""
    docs = spark.range(60).select(F.when(F.col("id") % 3 == 0, None).otherwise(F.col("id") % 2).alias("doc_id"), F.concat(F.lit("t"), "id").alias("text"))
    got = scaled_sketch.with_next(docs, ["text"], per_range=4).collect()
    assert sorted(r.text for r in got) == sorted(r.next_text for r in got) == sorted(f"t{i}" for i in range(60))
    order = {None: 0, 0: 1, 1: 2}
    place = {r.text: order[r.doc_id] for r in got}
    assert sum(place[r.next_text] < place[r.text] for r in got) == 1


# --- 3 -----------------------------------------------------------------------


def test_license_scan(spark, tmp_path):
    mit = licenses.TEMPLATES["mit-permission"].split()
    cut = " ".join(mit[:40] + ["changed"] + mit[41:])  # five shingles less
    rows = [(1, "x " * 100 + cut + " y" * 100, "en", "a"), (2, " ".join(mit[:30]), "en", "a"), (3, "foo\nALL RIGHTS RESERVED\nbar", "en", "a"), (4, None, None, None), (5, "clean words only " * 50, "en", "a"), (3, "foo\nALL RIGHTS RESERVED\nbar", "en", "a")]
    got = sorted((r.doc_id, r.license, r.containment) for r in registry.QUERIES["op3_license_scan"](spark, write(tmp_path, rows)).collect())
    n = len(mit) - 4
    assert got == [(1, "mit-permission", (n - 5) / n), (3, "all-rights-reserved", 1.0), (3, "all-rights-reserved", 1.0)]


def test_license_scan_equals_brute_force(spark, small):
    lib, want = licenses.Library(licenses.TEMPLATES), set()
    for d in pq.read_table(f"{small}/documents.parquet").to_pylist():
        keys = np.array([k for w in (d["text"] or "").split() if (k := licenses.word_key(w))], np.uint64)
        for (n, _), c in lib.classes.items():
            h = licenses.shingle_hashes(keys, n)
            for number, shingles in c["templates"]:
                share, place = licenses.containment(h, shingles, c["window"])
                if share >= 0.8:
                    want.add((d["doc_id"], lib.names[number], share, place))
    assert {tuple(r) for r in registry.QUERIES["op3_license_scan"](spark, small).collect()} == want


# --- 4 -----------------------------------------------------------------------


def test_media_round_trip(spark, edge):
    by = {}
    for r in registry.QUERIES["op4_telephony_media"](spark, edge).collect():
        by.setdefault(r.doc_id, r)
    for i, t, *_ in EDGE:
        full = telephony.padded((t or "").encode())
        r = by[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len((t or "").encode()), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-64:]))
    assert by[1].media_sha256 == by[2].media_sha256 and by[1].feature == by[2].feature


def test_codecs():
    mu, a = telephony.mulaw_table(), telephony.alaw_table()
    assert (int(mu[0]), int(mu[128]), int(mu[255]), int(mu[127])) == (-32124, 32124, 0, 0)
    assert (int(a[0x55]), int(a[0xD5]), int(a[0x2A]), int(a[0xAA])) == (-8, 8, -32256, 32256)
    data = np.random.default_rng(0).integers(0, 256, 640).astype(np.uint8)
    for row, out in zip(data.reshape(-1, 64), telephony.adpcm_blocks(data)):
        value, index = int(np.int16(np.uint16(int(row[0]) | int(row[1]) << 8))), min(int(row[2]), 88)
        want = [value]
        for byte in row[4:].tolist():
            for code in (byte & 15, byte >> 4):
                step = telephony.STEP_SIZES[index]
                diff = (step >> 3) + (step >> 2 if code & 1 else 0) + (step >> 1 if code & 2 else 0) + (step if code & 4 else 0)
                value = max(-32768, min(32767, value - diff if code & 8 else value + diff))
                index = max(0, min(88, index + telephony.INDEX_MOVES[code & 7]))
                want.append(value)
        assert out.tolist() == want
    tone = (8000 * np.sin(2 * np.pi * 440 * np.arange(4000) / 8000)).astype(np.int16)
    for rate in (16000, 6000, 8000):
        y = telephony.resample(tone, 8000, rate)
        assert np.abs(y - 8000 * np.sin(2 * np.pi * 440 * np.arange(len(y)) / rate))[60:-60].max() < 10
    with pytest.raises(ValueError):
        telephony.from_wave(b"nothing")


def test_decoded_column(spark, edge):
    media = telephony.packed(spark.read.parquet(f"{edge}/documents.parquet"))
    pcm = {r.doc_id: (r.rate, bytes(r.pcm)) for r in telephony.decoded(media).collect()}
    assert {rate for rate, _ in pcm.values()} == {16000}
    for r in registry.QUERIES["op4_telephony_media"](spark, edge).collect():
        assert (r.rate, bytes(r.pcm)) == pcm[r.doc_id]
        assert f"crc={zlib.crc32(bytes(r.pcm)):08x}" in r.feature and f"n={len(r.pcm) // 2};" in r.feature


# --- 5 -----------------------------------------------------------------------


def test_wordpiece_automaton():
    vocabulary = wordpiece.read_vocabulary(P.path("byte_bpe_50k.json"))
    known, automaton = set(vocabulary), wordpiece.Automaton(vocabulary)
    rng = np.random.default_rng(1)
    words = [b"", b" unbelievable", b" " + b"x" * 400, "ßtraße日本".encode(), *[bytes(rng.integers(97, 123, n).astype(np.uint8)) for n in rng.integers(1, 40, 300)]]

    def greedy(w):
        n = 0
        while w:
            k = next(k for k in range(len(w), 0, -1) if w[:k] in known)
            w, n = w[k:], n + 1
        return n

    assert automaton.counts(words).tolist() == [greedy(w) for w in words]
    with pytest.raises(ValueError):
        wordpiece.Automaton([b"a"])


def greedy_pieces(word, known, longest):
    n = 0
    while word:
        k = next(k for k in range(min(len(word), longest), 0, -1) if word[:k] in known)
        word, n = word[k:], n + 1
    return n


@pytest.mark.parametrize("folder", ["edge", "small"])
def test_wordpiece_query_equals_greedy(spark, request, folder):
    import regex

    path = request.getfixturevalue(folder)
    known = set(wordpiece.read_vocabulary(P.path("byte_bpe_50k.json")))
    longest = max(map(len, known))
    want = []
    for d in pq.read_table(f"{path}/documents.parquet").to_pylist():
        words = [w for w in re.split(r"[\x09-\x0D\x20]+", d["text"] or "") if w]
        per = []
        for w in words:
            parts = regex.findall(r"[\p{L}\p{N}\p{M}]+|[^\p{L}\p{N}\p{M}]", w)
            per.append(sum(greedy_pieces((" " * (i == 0) + p).encode(), known, longest) for i, p in enumerate(parts)))
        want.append((d["doc_id"], len(d["text"] or ""), len(words), sum(per), max(per, default=0)))
    got = [tuple(r)[:5] for r in registry.QUERIES["op5_wordpiece_counts"](spark, path).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)


# --- 6 -----------------------------------------------------------------------


def test_language_accuracy(spark):
    docs = "/root/testdata/sf0.01/documents.parquet"
    langs = {d["doc_id"]: d["lang"] for d in pq.read_table(docs).to_pylist()}
    rows = registry.QUERIES["op6_language_id"](spark, "/root/testdata/sf0.01").collect()
    held = [r for r in rows if r.held_out]
    assert held and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    assert np.mean([langs[r.doc_id] == r.lang_pred for r in held]) > 0.98
    assert all(0 <= r.score <= 1 for r in rows)


def test_language_undetermined(spark, edge):
    got = {r.doc_id: r.lang_pred for r in registry.QUERIES["op6_language_id"](spark, edge).collect()}
    assert {i for i, p in got.items() if p == "und"} == {3, 4, 5, 11}


def test_language_sees_nothing_but_text(spark, tmp_path):
    """With doc_id, source and lang of the rows to predict replaced, the same texts get the same languages."""
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    model = language.fit(rows.where(~language.held_out()))
    told = {r.text: r.lang_pred for r in language.predicted(rows, model).collect()}
    other = rows.select((F.col("doc_id") * 7 + 5).alias("doc_id"), "text", F.lit("xx").alias("lang"), F.reverse("source").alias("source"))
    assert {r.text: r.lang_pred for r in language.predicted(other, model).collect()} == told


def test_language_sample_is_not_filled_by_copies(spark):
    """One text copied a thousand times is one training text."""
    rows = [(i, "ein sehr deutscher satz mit vielen worten", "de") for i in range(1000)] + [(2000 + i, f"noch ein anderer deutscher text nummer {i} und mehr davon", "de") for i in range(40)]
    rows += [(3000 + i, f"an english text with the number {i} and some more of it", "en") for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language.fit(docs, per_language=20)
    got = {r.text: r.lang_pred for r in language.predicted(docs, model).collect()}
    assert all((p == "de") == ("deutscher" in t) for t, p in got.items())


def test_language_without_labels(spark):
    docs = spark.createDataFrame([(1, "some words", None)], "doc_id long, text string, lang string")
    assert language.predicted(docs, language.fit(docs)).first().lang_pred == "und"


# --- 7 -----------------------------------------------------------------------


def test_rans_codec():
    rng = np.random.default_rng(2)
    for n in (0, 1, 2047, 2048, 2049, 1_200_000):
        ids = (rng.zipf(1.3, n) % 5000).astype(np.int64)
        table = rans.Table.of_counts(np.bincount(ids, minlength=1 << 16))
        assert int(table.freq.sum()) == 1 << rans.SCALE
        words, states, places = rans.encode(ids, table)
        assert (rans.decode(words, states, places, n, table) == ids).all()
        at = rans.EVERY * rans.LANES
        if n > at:
            assert (rans.decode(words, states, places, n, table, first=1) == ids[at:]).all()
            assert (rans.decode(words, states, places, n, table, last=1) == ids[:at]).all()
    data = bytearray(rans.pack(np.array([1]), np.array([n]), ids, table))
    data[-100] ^= 1
    with pytest.raises(ValueError):
        rans.unpack(bytes(data), table)


def test_token_id_files(spark, edge):
    tok = pytest.importorskip("tokenizers").Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    at, want = 0, []
    for i, t, *_ in sorted(EDGE, key=lambda e: (e[0] is not None, e[0] or 0, e[1] or "")):
        ids = tok.encode(t or "", add_special_tokens=False).ids + [2]
        want.append((i, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    got = [tuple(r)[:4] for r in registry.QUERIES["op7_rans_token_ids"](spark, edge).collect()]
    assert sorted(got, key=lambda r: r[1]) == want


# --- 8 -----------------------------------------------------------------------


def brute_components(rows):
    fps = [(r.doc_id, int(r.fingerprint, 16)) for r in rows]
    root = list(range(len(fps)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, (_, a) in enumerate(fps):
        for j in range(i):
            if bin(a ^ fps[j][1]).count("1") <= 2:
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    least = {}
    for i, (d, _) in enumerate(fps):
        least[find(i)] = min(d, least.get(find(i), d))
    return [(d, least[find(i)]) for i, (d, _) in enumerate(fps)]


def plain_fingerprint(text):
    """Bit by bit, from the contract."""
    import xxhash

    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", low) if w]
    if not words:
        return "0" * 16
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + 3]).encode(), 42) for i in range(max(1, len(words) - 2))]
    return f"{sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes)):016x}"


@pytest.mark.parametrize("folder", ["edge", "small"])
def test_simhash_fingerprints(spark, request, folder):
    path = request.getfixturevalue(folder)
    want = [(d["doc_id"], plain_fingerprint(d["text"])) for d in pq.read_table(f"{path}/documents.parquet").to_pylist()]
    got = [(r.doc_id, r.fingerprint) for r in registry.QUERIES["op8_simhash_near_dedup"](spark, path).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)


def test_simhash_in_many_shards(spark, small):
    """Tiny shards, and all of them taken for dense balls, give the same groups."""
    prints = simhash.stored(simhash.fingerprints(spark.read.parquet(f"{small}/documents.parquet")), "prints")
    got = lambda **kw: {(r.doc_id, r.component_id) for r in simhash.components(prints, **kw).collect()}
    assert got() == got(sample=200, per_shard=10) == got(per_shard=10, dense=0)


def test_simhash_groups(spark, small):
    rows = registry.QUERIES["op8_simhash_near_dedup"](spark, small).collect()
    assert sorted((r.doc_id, r.component_id) for r in rows) == sorted(brute_components(rows))


def test_simhash_edge(spark, edge):
    got = {r.doc_id: r for r in registry.QUERIES["op8_simhash_near_dedup"](spark, edge).collect()}
    assert got[2].component_id == 1 and got[14].component_id == 14 and got[4].component_id == 3 and got[5].fingerprint == "0" * 16 and got[None].component_id is None


@pytest.mark.parametrize("spread", [64, 10])
def test_tree_finds_all_links(spread):
    """Scattered fingerprints and a dense ball, through tree and shards, against all pairs."""
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 40).astype(np.uint64)
    flips = (np.uint64(1) << rng.integers(0, spread, (1500, 2)).astype(np.uint64)).sum(1)
    fps = np.unique(np.concatenate([base, base[rng.integers(0, 40, 1500)] ^ flips]))
    a, b = np.nonzero(np.triu(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 2, 1))
    want = simhash.forest(np.stack([fps[a], fps[b]], 1))
    assert (simhash.forest(simhash.links(fps, leaf=16)) == want).all()
    assert (simhash.forest(simhash.dense_links(fps)) == want).all()
    shard, some = simhash.route(simhash.build(fps[:300], 40), fps)
    parts = [simhash.links(some[shard == s], leaf=16) for s in np.unique(shard)]
    assert (simhash.forest(np.concatenate(parts)) == want).all()


# --- 9 -----------------------------------------------------------------------


def test_raking_meets_marginals(spark, small):
    rows = raking.described(spark.read.parquet(f"{small}/documents.parquet"))
    cells = rows.groupBy(*raking.DIMENSIONS).agg(F.sum("n_tokens").alias("n_tokens"))
    targets = raking.default_targets(cells)
    assert raking.gap(raking.wanted(cells, targets)) > 0.01
    fit = raking.fitted(cells, targets, rounds=60, tolerance=1e-6)
    for d in raking.DIMENSIONS:
        want = {r.value: r.target for r in targets[d].collect()}
        total = sum(want.values())
        have = {r[0]: r.s for r in fit.groupBy(d).agg(F.sum("share").alias("s")).collect() if r.s > 0}
        assert max(abs(have[v] - want[v] / total) for v in want) < 1e-6


def test_given_targets(spark):
    rows = spark.createDataFrame([(i, "a" if i % 3 else "b", "en" if i % 2 else "de", "t", 10) for i in range(600)], "doc_id long, source string, lang string, topic string, n_tokens long")
    mk = lambda **kw: spark.createDataFrame(list(kw.items()), "value string, target double")
    out = raking.mixed(rows, {"source": mk(a=0.5, b=0.5), "lang": mk(en=0.7, de=0.3), "topic": mk(t=1.0)}, keep=0.3)
    share = {r.source: r.w for r in out.groupBy("source").agg(F.sum(F.col("n_tokens") * F.col("probability") * F.col("weight")).alias("w")).collect()}
    assert abs(share["a"] / (share["a"] + share["b"]) - 0.5) < 0.01
    assert 100 < out.where("sampled").count() < 260


def test_draws_meet_the_marginals(spark):
    """Whole copies and a drawn rest: the tokens of the drawn documents stand to each other as the targets do."""
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    base, drawn = (raking.stored(raking.described(x), "mix") for x in (docs, raking.sampled(docs)))
    total = drawn.agg(F.sum("n_tokens")).first()[0]
    assert abs(total / base.agg(F.sum("n_tokens")).first()[0] - raking.KEEP) < 0.03
    for d in raking.DIMENSIONS:
        want = {r[0]: r[1] ** 0.5 for r in base.groupBy(d).agg(F.sum("n_tokens")).collect() if r[1]}
        have = {r[0]: r[1] / total for r in drawn.groupBy(d).agg(F.sum("n_tokens")).collect()}
        assert max(abs(have.get(v, 0) - x / sum(want.values())) for v, x in want.items()) < 0.015, d


def test_mix_edge_values(spark, edge):
    got = [r for r in registry.QUERIES["op9_raked_mix"](spark, edge).collect()]
    words = {e[0]: len((e[1] or "").split()) for e in EDGE}
    for r in got:
        assert r.n_tokens == words[r.doc_id] and 0 <= r.probability <= 1
        if r.doc_id in (3, 4):
            assert (r.topic, r.n_tokens, r.source) == ("empty", 0, "")
        if r.n_tokens:
            assert abs(r.probability * r.weight - raking.KEEP * r.ratio) < 1e-4 * max(1, r.ratio)
    assert len({(r.sampled, r.probability) for r in got if r.doc_id == 1}) == 1


# --- 10 ----------------------------------------------------------------------


def test_bpe_equals_library(spark, edge):
    tiktoken = pytest.importorskip("tiktoken")
    path = P.path("byte_bpe_multi_50k.tiktoken")
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(path), special_tokens={})
    got = {r.doc_id: r for r in registry.QUERIES["op10_duckdb_bpe"](spark, edge).collect()}
    for i, t, *_ in EDGE:
        ids = enc.encode_ordinary(t or "")
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()


def test_bpe_of_words_without_a_break():
    """A million letters, one repeated, two in turn: they end, in bounded memory, and equal the library where it ends."""
    tiktoken = pytest.importorskip("tiktoken")
    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    coder = bpe.Coder(ranks, P.PATTERN)
    rng = np.random.default_rng(4)
    letters = lambda n, m: bytes(rng.integers(97, 97 + m, n).astype(np.uint8)).decode()
    texts = [letters(1_000_000, 26), letters(30_000, 3), "a" * 20_000, "ab" * 10_000, "x" * 257, "thequickbrownfox" * 900, "é" * 3_000, "日本語" * 2_000, letters(600, 2) + " " + letters(600, 2)]
    ids, sizes = pieces.encode_texts(pa.array(texts), coder.encode)
    assert coder.decode(ids, sizes, rows=50_000) == [t.encode() for t in texts]
    at = 0
    for t, n in zip(texts, sizes.tolist()):
        assert ids[at : at + n].tolist() == enc.encode_ordinary(t), t[:20]
        at += n
    assert not [w for w in (*coder.known, *coder.older) if len(w) > bpe.LONG]


def test_bpe_words_are_forgotten_and_learnt_again(monkeypatch):
    tiktoken = pytest.importorskip("tiktoken")
    monkeypatch.setattr(bpe, "CACHE", 40)
    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    coder = bpe.Coder(ranks, P.PATTERN)
    learnt = []
    learn = coder.learn
    coder.learn = lambda new, known: (learnt.append(set(new)), learn(new, known))
    for turn in range(12):
        texts = ["oftenseenword " * 3 + " ".join(f"rareword{turn}x{i}qz" for i in range(30)), "", f"again{turn % 5}zq"]
        ids, sizes = pieces.encode_texts(pa.array(texts), coder.encode)
        assert [x.tolist() for x in np.split(ids, np.cumsum(sizes)[:-1])] == [enc.encode_ordinary(t) for t in texts]
        assert len(coder.known) <= 40 and len(coder.older) <= 40 + 200
    often = [t for t, words in enumerate(learnt) if " oftenseenword" in words or "oftenseenword" in words]
    assert often == [0]


def test_pieces_against_whole_texts():
    tok = pytest.importorskip("tokenizers").Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    texts = ["a b", "a  b", " a", "a ", "", None, "x\n y", "x \ny", "it's a  \n\n b c", "é  ü z", " ", "x, y", "a (b), c", "d). e, f! 1,2, 3.", "don't; é, !!", "a b c  d"]
    encoder = rans.PieceEncoder(tok)
    for _ in range(2):  # the second time from what it remembers
        ids, sizes = pieces.encode_texts(pa.array(texts), encoder)
        at = 0
        for t, n in zip(texts, sizes):
            assert ids[at : at + n].tolist() == tok.encode(t or "", add_special_tokens=False).ids, t
            at += n
