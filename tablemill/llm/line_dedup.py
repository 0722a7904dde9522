"""Incremental, reversible line deduplication.

State of an index (tables in the shared store, all keyed by a 128-bit line digest):

* ``refs``: the exact references, one row per (line, document row); the smallest
  document of a line is its keeper.
* ``counts``: the exact reference counts, changes only; a line's count is their sum.
* ``filters``: one cuckoo filter per shard of the digest space, 16-bit
  fingerprints in buckets of four, one for each line that has a reference. A
  filter answers "never seen" without touching the exact tables; every "maybe"
  is settled by the exact counts, so filters never decide a result alone.

Insertion sends the batch's distinct lines to their shards. What the shard's
filter has never seen is added to it there and then; only the "maybe" lines join
the exact counts, and those that prove new (a shared fingerprint) are added after.
Deletion lowers the counts, and takes a fingerprint out of its filter once the
last reference is gone, so that deleting a batch restores the state before it.

All tables grow by files of changes; nothing is rewritten before ``compact``. A
version is one small manifest that names its files and appears by a rename, so a
run that dies leaves the last version intact, and an index can be opened again.
The number of shards follows the number of lines: a filter holds about
``PER_SHARD`` of them, beyond four times that all filters are built anew.

Defined results: a null or empty text is one empty line; rows with a null
document id are kept whole and hold no reference; repeated rows of an id are one
document (counts are of rows); extra columns pass through ``clean`` untouched.
"""

from __future__ import annotations

import hashlib
import json
import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tablemill.llm.common import columns, drop_path, forget, free_name, lean, put_text, stored, texts_in, whole, work_path

BLANK = b" \t\n\x0b\x0c\r"
MIN_CHARS = 10
SLOTS = 4
LOAD = 0.84
PER_SHARD = 1_000_000
BATCHES = 2


# --- lines -----------------------------------------------------------------


def line_digest(line: bytes, min_chars: int = MIN_CHARS) -> bytes | None:
    """Digest of a line's key, or None where the key is too short to count."""
    key = line.strip(BLANK).lower()
    if len(key) < min_chars or (len(key) < 4 * min_chars and len(key.decode("utf-8", "replace")) < min_chars):
        return None
    return xxhash.xxh3_128_digest(key)


def line_rows(docs: DataFrame, min_chars: int = MIN_CHARS, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """(k, doc_id, n): the countable line digests of each document row, each once."""
    shape = columns("k binary, doc_id long, n int")

    def rows(batches):
        for b in batches:
            for ids, texts in _slices(b):
                ks, owners, ns = [], [], []
                for i, t in zip(ids, texts):
                    seen: dict[bytes, int] = {}
                    for line in t.split(b"\n"):
                        if k := line_digest(line, min_chars):
                            seen[k] = seen.get(k, 0) + 1
                    ks += seen.keys()
                    ns += seen.values()
                    owners += [i] * len(seen)
                yield pa.RecordBatch.from_arrays([pa.array(ks, pa.binary()), pa.array(owners, pa.int64()), pa.array(ns, pa.int32())], schema=shape)

    picked = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).where("doc_id is not null")
    return picked.mapInArrow(lean(rows), "k binary, doc_id long, n int")


def _slices(batch: pa.RecordBatch, rows: int = 2000):
    for at in range(0, batch.num_rows, rows):
        part = batch.slice(at, rows)
        yield part.column(0).to_pylist(), whole(part.column(1))


# --- cuckoo filter ---------------------------------------------------------


def _spread(x: np.ndarray) -> np.ndarray:
    """A 64-bit mixer (xor-shift and multiply)."""
    x = x.astype(np.uint64)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    return x


class CuckooFilter:
    """Partial-key cuckoo filter, vectorised; buckets are a power of two."""

    def __init__(self, buckets: int, table: np.ndarray | None = None, stash: list[int] | None = None):
        self.mask = np.uint64(buckets - 1)
        self.table = np.zeros((buckets, SLOTS), np.uint16) if table is None else table
        self.stash = list(stash or [])

    @classmethod
    def sized(cls, items: int) -> CuckooFilter:
        need = max(1, int(np.ceil(items / (SLOTS * LOAD))))
        return cls(1 << (need - 1).bit_length())

    def _place(self, digests: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Fingerprint (never 0) and first bucket of each digest (two uint64 a row)."""
        mark = ((digests[:, 0] & np.uint64(0xFFFF)) % np.uint64(65535) + np.uint64(1)).astype(np.uint16)
        return mark, _spread(digests[:, 1]) & self.mask

    def _other(self, at: np.ndarray, mark: np.ndarray) -> np.ndarray:
        return at ^ (_spread(mark.astype(np.uint64) + np.uint64(1)) & self.mask)

    def has(self, digests: np.ndarray) -> np.ndarray:
        mark, at = self._place(digests)
        hit = (self.table[at] == mark[:, None]).any(1) | (self.table[self._other(at, mark)] == mark[:, None]).any(1)
        if self.stash:
            hit |= np.isin(mark, np.array(self.stash, np.uint16))
        return hit

    def add(self, digests: np.ndarray, rounds: int = 500) -> None:
        """Insert all; one item a bucket and round, evicting in lockstep. Leftovers go to a stash."""
        mark, at = self._place(digests)
        for turn in range(rounds):
            if not len(mark):
                return
            left = np.ones(len(mark), bool)
            for try_at in (at, self._other(at, mark)):
                todo = np.flatnonzero(left)
                _, first = np.unique(try_at[todo], return_index=True)
                pick = todo[first]
                free = self.table[try_at[pick]] == 0
                ok = free.any(1)
                pick, slot = pick[ok], free[ok].argmax(1)
                self.table[try_at[pick], slot] = mark[pick]
                left[pick] = False
            mark, at = mark[left], at[left]
            if not len(mark):
                return
            full = ~((self.table[at] == 0).any(1) | (self.table[self._other(at, mark)] == 0).any(1))
            todo = np.flatnonzero(full)
            if len(todo):
                _, first = np.unique(at[todo], return_index=True)
                pick, slot = todo[first], (turn + mark[todo[first]]) % SLOTS
                out = self.table[at[pick], slot].copy()
                self.table[at[pick], slot] = mark[pick]
                mark[pick] = out
                at[pick] = self._other(at[pick], out)
        self.stash += [int(x) for x in mark]

    def remove(self, digests: np.ndarray) -> None:
        """Take out one copy of each digest's fingerprint; they must have been inserted."""
        mark, first = self._place(digests)
        left = np.ones(len(mark), bool)
        for at in (first, self._other(first, mark)):
            todo = np.flatnonzero(left)
            while len(todo):  # equal fingerprints of a bucket one after the other
                _, one = np.unique(at[todo] * np.uint64(65536) + mark[todo], return_index=True)
                pick = todo[one]
                held = self.table[at[pick]] == mark[pick][:, None]
                ok = held.any(1)
                if not ok.any():
                    break
                pick = pick[ok]
                self.table[at[pick], held[ok].argmax(1)] = 0
                left[pick] = False
                todo = todo[left[todo]]
        for m in mark[left].tolist():
            if m in self.stash:
                self.stash.remove(m)

    def dump(self) -> bytes:
        return np.array([len(self.table), len(self.stash)], "<u4").tobytes() + np.array(self.stash, "<u2").tobytes() + self.table.astype("<u2").tobytes()

    @classmethod
    def load(cls, data: bytes) -> CuckooFilter:
        buckets, extra = np.frombuffer(data, "<u4", 2)
        stash = np.frombuffer(data, "<u2", int(extra), 8)
        table = np.frombuffer(data, "<u2", int(buckets) * SLOTS, 8 + 2 * int(extra)).reshape(-1, SLOTS).astype(np.uint16)
        return cls(int(buckets), table, stash.tolist())


def digest_words(keys: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(keys), "<u8").reshape(-1, 2) if keys else np.zeros((0, 2), np.uint64)


def shard_of(words: np.ndarray, shards: int) -> np.ndarray:
    return ((words[:, 0] >> np.uint64(32)) % np.uint64(shards)).astype(np.int64)


def shard_column(shards: int, k: str = "k") -> Column:
    """The same shard number on the JVM side: bytes 4 to 7 of the digest, little end first."""
    word = F.conv(F.concat(*[F.hex(F.substring(k, i, 1)) for i in (8, 7, 6, 5)]), 16, 10).cast("long")
    return F.pmod(word, F.lit(shards)).cast("int")


FILTER_ROWS = "shard int, k binary, items long, filter binary"


def update_shard(key, moved: pa.Table, held: pa.Table) -> pa.Table:
    """A shard's filter after its lines (``sign`` 1: may be new, 2: is new, -1: is gone), and the lines it may have known.

    A filter without room is given up (``items`` -1): its shard is built anew from the exact counts.
    """
    now = CuckooFilter.load(held.column("filter")[0].as_py()) if held.num_rows else None
    items = held.column("items")[0].as_py() if held.num_rows else 0
    words, sign = digest_words(moved.column("k").to_pylist()), moved.column("sign").to_numpy()
    maybe = np.zeros(len(words), bool)
    if now is not None:
        maybe = now.has(words) & (sign == 1)
        now.remove(words[sign < 0])
    new = words[(sign > 0) & ~maybe]
    items += len(new) - int((sign < 0).sum())
    now = CuckooFilter.sized(2 * items) if now is None else now
    data = b""
    if items > now.table.size * LOAD:
        items = -1
    else:
        now.add(new)
        data = now.dump()
    ks = moved.column("k").filter(pa.array(maybe)).to_pylist()
    n, shard = len(ks), key[0].as_py()
    return pa.table({"shard": pa.array([shard] * (n + 1), pa.int32()), "k": pa.array([*ks, None], pa.binary()), "items": pa.array([None] * n + [items], pa.int64()), "filter": pa.array([None] * n + [data], pa.binary())})


# --- index -----------------------------------------------------------------

LINES = "k binary, doc_id long, n int"
COUNTS = "k binary, low long, high long, n long"


def shards_for(n_keys: int, per_shard: int = PER_SHARD) -> int:
    return max(32, -(-n_keys // per_shard))


class LineIndex:
    """Long-lived index over batches under ``path``: ``insert`` and ``delete`` return to any earlier state.

    The newest manifest in ``path/versions`` names the files of each kind with the
    version they came in. A path that holds an index is opened with all its versions.
    """

    def __init__(self, spark: SparkSession, path: str | None = None, min_chars: int = MIN_CHARS, per_shard: int = PER_SHARD):
        self.spark, self.min_chars, self.per_shard = spark, min_chars, per_shard
        self.path = path or work_path(spark, "line-index")
        found = texts_in(spark, f"{self.path}/versions")
        self.now = json.loads(found[max(found)]) if found else {"version": 0, "shards": 0, "lines": 0, "refs": [], "gone": [], "counts": [], "filters": [], "twice": []}

    @property
    def version(self) -> int:
        return self.now["version"]

    def _write(self, kind: str, rows: DataFrame) -> str:
        path = f"{self.path}/{kind}-{uuid.uuid4().hex}"
        rows.write.option("compression", "zstd").parquet(path)
        return path

    def _commit(self, **added) -> None:
        new = {**self.now, "version": self.version + 1}
        for kind, value in added.items():
            new[kind] = [*new[kind], [new["version"], value]] if isinstance(value, str) else value
        put_text(self.spark, f"{self.path}/versions/{new['version']:012d}.json", json.dumps(new))
        self.now = new

    def _all(self, kind: str, schema: str) -> DataFrame:
        """All files of a kind, with the version ``v`` each row came in."""
        out = self.spark.createDataFrame([], f"{schema}, v long")
        for v, path in self.now[kind]:
            out = out.unionByName(self.spark.read.schema(schema).parquet(path).withColumn("v", F.lit(v).cast("long")))
        return out

    def refs(self) -> DataFrame:
        """The references of documents that are still in."""
        out = self._all("refs", LINES)
        if self.now["gone"]:
            gone = self._all("gone", "doc_id long").groupBy(F.col("doc_id").alias("gone_id")).agg(F.max("v").alias("gone_v"))
            out = out.join(gone, (F.col("doc_id") == F.col("gone_id")) & (F.col("gone_v") > F.col("v")), "left_anti")
        return out.drop("v")

    def filters(self) -> DataFrame:
        """(shard, items, filter): the newest of each shard."""
        newest = F.max_by(F.struct("items", "filter"), "v").alias("f")
        return self._all("filters", "shard int, items long, filter binary").groupBy("shard").agg(newest).select("shard", "f.items", "f.filter")

    def counted(self, among: DataFrame | None = None, counts: DataFrame | None = None) -> DataFrame:
        """(k, n): lines with a reference, of all or ``among`` some."""
        rows = self._all("counts", COUNTS) if counts is None else counts
        if among is not None:
            rows = rows.join(among.select("k"), "k", "left_semi")
        return rows.groupBy("k").agg(F.sum("n").alias("n")).where("n > 0")

    def _moved(self, lines: DataFrame, sign: int, filters: DataFrame, shards: int) -> DataFrame:
        moves = lines.select("k", F.lit(sign).alias("sign"), shard_column(shards).alias("shard"))
        return stored(moves.groupBy("shard").cogroup(filters.groupBy("shard")).applyInArrow(update_shard, FILTER_ROWS), "filters-moved")

    def _built(self, rows: list[DataFrame], counts: DataFrame, shards: int) -> DataFrame:
        """Filters of moved shards, the later list entry first; those without room from ``counts``."""
        kept, full = None, None
        for moved in rows:
            own = moved.where("k is null").select("shard", "items", "filter")
            kept = own if kept is None else kept.unionByName(own.join(kept.select("shard"), "shard", "left_anti"))
        full = kept.where("items < 0").select("shard")
        if not full.take(1):
            return kept
        again = self.counted(counts=counts.select(shard_column(shards).alias("shard"), "k", "n").join(full, "shard", "left_semi"))
        fresh = self._moved(again, 2, self.spark.createDataFrame([], "shard int, items long, filter binary"), shards)
        return kept.where("items >= 0").unionByName(fresh.where("k is null").select("shard", "items", "filter"))

    def insert(self, docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
        """Add a batch; returns (k) of its lines that were known before."""
        refs = self._write("refs", line_rows(docs, self.min_chars, text, doc_id))
        lines = self.spark.read.schema(LINES).parquet(refs)
        batch = reference_counts(lines)
        counts = self._write("counts", batch)
        batch = self.spark.read.schema(COUNTS).parquet(counts)
        total = self.now["lines"] + batch.count()
        every = self._all("counts", COUNTS).drop("v").unionByName(batch)
        if self.now["shards"] and total <= 4 * self.per_shard * self.now["shards"]:
            shards = self.now["shards"]
            moved = [self._moved(batch, 1, self.filters(), shards)]
            maybe = moved[0].where("k is not null").select("k")
            known = stored(maybe.join(self.counted(maybe), "k", "left_semi"), "known")
            false = maybe.join(known, "k", "left_anti")
            if false.take(1):
                held = moved[0].where("k is null and items >= 0").select("shard", "items", "filter")
                moved.insert(0, self._moved(false.withColumn("of", shard_column(shards)).join(held.select(F.col("shard").alias("of")), "of", "left_semi"), 2, held, shards))
        else:  # the first batch, or too many lines for this number of shards: all filters are built from the counts
            shards = shards_for(total, self.per_shard)
            maybe = batch.select("k")
            known = stored(maybe.join(self.counted(maybe), "k", "left_semi") if self.version else maybe.limit(0), "known")
            moved = [self._moved(self.counted(counts=every), 2, self.spark.createDataFrame([], "shard int, items long, filter binary"), shards)]
        filters = self._write("filters", self._built(moved, every, shards))
        twice = self._write("twice", batch.where("low < high").select("k").unionByName(known).distinct())
        for rows in moved:
            forget(rows)
        if shards != self.now["shards"]:
            self.now = {**self.now, "filters": []}
        self._commit(refs=refs, counts=counts, filters=filters, twice=twice, shards=shards, lines=total)
        return known

    def delete(self, doc_ids: DataFrame) -> None:
        """Take documents out; a line that loses its last reference leaves its filter too."""
        gone = self._write("gone", doc_ids.select(F.col("doc_id").cast("long")).where("doc_id is not null").distinct())
        lost = self.refs().join(self.spark.read.schema("doc_id long").parquet(gone), "doc_id", "left_semi").groupBy("k").agg(F.count("*").alias("n"))
        shards = self.now["shards"] or 1
        counts = self._write("counts", lost.select("k", F.lit(None).cast("long").alias("low"), F.lit(None).cast("long").alias("high"), (-F.col("n")).alias("n")))
        change = self.spark.read.schema(COUNTS).parquet(counts)
        every = self._all("counts", COUNTS).drop("v").unionByName(change)
        dead = change.select("k").join(self.counted(change, every), "k", "left_anti")
        moved = self._moved(dead, -1, self.filters().join(dead.select(shard_column(shards).alias("shard")).distinct(), "shard", "left_semi"), shards)
        filters = self._write("filters", self._built([moved], every, shards))
        forget(moved)
        self._commit(gone=gone, counts=counts, filters=filters)

    def repeats(self) -> DataFrame:
        """(k, keeper, n_refs) of lines now held by two documents and more.

        Only lines that some batch held twice or found known can be such lines. While no
        document has left, each batch's least and greatest document tell the whole;
        after that the references do. Both are summed up before they are shuffled.
        """
        some = self._all("twice", "k binary").select("k").distinct()
        if self.now["gone"]:
            held = self.refs().groupBy("k").agg(F.min("doc_id").alias("keeper"), F.max("doc_id").alias("last"), F.count("*").alias("n_refs"))
        else:
            held = self._all("counts", COUNTS).groupBy("k").agg(F.min("low").alias("keeper"), F.max("high").alias("last"), F.sum("n").alias("n_refs"))
        return held.where("keeper < last").join(some, "k", "left_semi").drop("last")

    def dropped(self) -> DataFrame:
        """(doc_id, gone): digests that each document loses, as one string of 32 hexadecimal digits each."""
        lost = self.refs().join(self.repeats().select("k", "keeper"), "k").where("doc_id > keeper")
        return lost.groupBy("doc_id").agg(F.array_join(F.collect_set(F.hex("k")), "").alias("gone"))

    def compact(self) -> None:
        """One file set of each kind instead of all changes; earlier versions go."""
        old = dict(self.now)
        refs, counts = self._write("refs", self.refs()), self._write("counts", self._all("counts", COUNTS).groupBy("k").agg(F.min("low").alias("low"), F.max("high").alias("high"), F.sum("n").alias("n")).where("n > 0"))
        filters, twice = self._write("filters", self.filters()), self._write("twice", self.repeats().select("k"))
        lines = self.spark.read.schema(COUNTS).parquet(counts).count()
        for kind in ("refs", "counts", "filters", "twice", "gone"):
            self.now[kind] = []
        self._commit(refs=refs, counts=counts, filters=filters, twice=twice, lines=lines)
        for kind in ("refs", "counts", "filters", "twice", "gone"):
            for _, path in old[kind]:
                drop_path(self.spark, path)
        for v in range(1, self.version):
            drop_path(self.spark, f"{self.path}/versions/{v:012d}.json")

    def destroy(self) -> None:
        drop_path(self.spark, self.path)


def reference_counts(lines: DataFrame) -> DataFrame:
    """(k, low, high, n): map-side combined, so a line in a third of all documents is no hot key."""
    return lines.groupBy("k").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high"), F.count("*").alias("n"))


def increment(docs: DataFrame, number: int, of: int, doc_id: str = "doc_id") -> DataFrame:
    """One of ``of`` parts that together are all documents."""
    return docs.where(F.pmod(F.xxhash64(doc_id), F.lit(of)) == number) if of > 1 else docs


def dropped_lines(docs: DataFrame, min_chars: int = MIN_CHARS, text: str = "text", doc_id: str = "doc_id", batches: int = BATCHES, per_shard: int = PER_SHARD) -> DataFrame:
    """(doc_id, gone): digests that each document loses.

    All documents enter a new index in ``batches`` increments; the result does not depend on how many.
    """
    index = LineIndex(docs.sparkSession, min_chars=min_chars, per_shard=per_shard)
    for number in range(batches):
        forget(index.insert(increment(docs, number, batches, doc_id), text, doc_id))
    out = stored(index.dropped(), "dropped-lines")
    index.destroy()
    return out


def split_text(text: bytes, gone: frozenset, min_chars: int) -> tuple[list[bytes], list[bytes]]:
    lines = text.split(b"\n")
    if not gone:
        return lines, lines
    return lines, [x for x in lines if line_digest(x, min_chars) not in gone]


def _gone(hexed: str | None) -> frozenset:
    data = bytes.fromhex(hexed or "")
    return frozenset(data[i : i + 16] for i in range(0, len(data), 16))


def apply_drops(docs: DataFrame, drops: DataFrame, fn, returns: str, text: str = "text", doc_id: str = "doc_id", min_chars: int = MIN_CHARS) -> DataFrame:
    """Join the digests to drop to their documents; ``fn(batch, lines, kept)`` makes the arrays to return."""
    owner, gone = free_name(docs, "_gone_id"), free_name(docs, "_gone")
    both = docs.join(drops.select(F.col("doc_id").alias(owner), F.col("gone").alias(gone)), F.col(doc_id).cast("long") == F.col(owner), "left").drop(owner)

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 2000):
                part = b.slice(at, 2000)
                pairs = [split_text(t, _gone(g), min_chars) for t, g in zip(whole(part.column(part.schema.get_field_index(text))), part.column(part.schema.get_field_index(gone)).to_pylist())]
                yield fn(part, [p[0] for p in pairs], [p[1] for p in pairs])

    return both.mapInArrow(lean(run), returns)


def digest(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256 of every document."""
    shape = columns("doc_id long, n_lines long, n_dropped long, kept_sha256 string")

    def rows(part, lines, kept):
        return pa.RecordBatch.from_arrays(
            [part.column(0).cast(pa.int64()), pa.array(map(len, lines), pa.int64()), pa.array([len(a) - len(b) for a, b in zip(lines, kept)], pa.int64()), pa.array([hashlib.sha256(b"\n".join(k)).hexdigest() for k in kept], pa.string())],
            schema=shape,
        )

    picked = docs.select("doc_id", "text")
    return apply_drops(picked, dropped_lines(picked, min_chars), rows, "doc_id long, n_lines long, n_dropped long, kept_sha256 string", min_chars=min_chars)


def clean(docs: DataFrame, min_chars: int = MIN_CHARS, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """The documents with repeated lines taken out of all but their keeper; other columns as they were."""
    schema = docs.schema

    def rows(part, lines, kept):
        whole_of = pa.array([b"\n".join(k) if len(k) < len(a) else None for a, k in zip(lines, kept)], pa.binary()).cast(pa.string())
        arrays = []
        for name in schema.names:
            col = part.column(part.schema.get_field_index(name))
            if name == text:
                changed = pa.array([len(k) < len(a) for a, k in zip(lines, kept)])
                col = pa.compute.if_else(changed, whole_of, col)
            arrays.append(col)
        return pa.RecordBatch.from_arrays(arrays, names=schema.names)

    return apply_drops(docs, dropped_lines(docs, min_chars, text, doc_id), rows, schema, text, doc_id, min_chars)


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP1_SQL = r"""
WITH t AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
l AS (SELECT r, doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS pos FROM t),
k AS (SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
s AS (SELECT key, min(doc_id) AS keeper FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) > 1),
m AS (SELECT k.r, k.doc_id, k.pos, k.line, s.keeper IS NOT NULL AND k.doc_id <> s.keeper AS gone FROM k LEFT JOIN s ON k.key = s.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (WHERE gone))::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM m GROUP BY r, doc_id
"""
