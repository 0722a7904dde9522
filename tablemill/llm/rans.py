"""Token ids in files coded with a static range asymmetric numeral system.

One table of symbol frequencies, counted over all documents and scaled to
2**20, is shared by all blocks. A block holds up to ``block`` ids, dealt to
interleaved lanes (lane j has ids j, j + lanes, ...) that share one stream of
32-bit words; each lane is a 64-bit state. Every ``every`` rows of lanes a
checkpoint keeps the states and the place in the stream, so that a reader can
start there and parts of a block can be decoded side by side. Blocks carry a
checksum of the payload and one of their ids.

A file set is a Parquet table of such blocks (``start, data``): any store that Spark writes can hold it, and its commit protocol keeps
it whole when executors are lost. ``data`` is a self-contained binary, see
``pack``.

Documents go in ascending id; rows of equal id in order of their ids' bytes;
null ids come first. A null or empty text holds only the end id.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tablemill.llm.common import columns, drop_path, lean, work_path
from tablemill.llm.pieces import begins, encode_texts, gather, laid_out, slices

SCALE = 20
LANES = 2048
BLOCK = 1 << 20
EVERY = 256
RANGES = 1 << 15
MAGIC = b"RANS0001"
LOW = np.uint64(1 << 31)
END_ID = 2
SPACE = "\u0120"  # the stand-in for a space in byte-level vocabularies


class Table:
    """Frequencies scaled to 2**20; every symbol that occurs keeps at least one."""

    def __init__(self, freq: np.ndarray):
        self.freq = freq.astype(np.uint64)
        self.start = np.concatenate([[0], np.cumsum(freq)[:-1]]).astype(np.uint64)
        self.slot: np.ndarray | None = None

    @classmethod
    def of_counts(cls, counts: np.ndarray) -> Table:
        """Largest remainder scaling, deterministic."""
        total, room = int(counts.sum()), 1 << SCALE
        if not total:
            return cls(np.concatenate([[room], np.zeros(max(0, len(counts) - 1), np.int64)]))
        exact = counts.astype(np.float64) * room / total
        freq = np.where(counts > 0, np.maximum(1, np.floor(exact)), 0).astype(np.int64)
        gap = room - int(freq.sum())
        if gap > 0:
            order = np.lexsort((np.arange(len(freq)), -(exact - freq) * (counts > 0)))
            freq[order[: min(gap, int((counts > 0).sum()))]] += 1
            freq[int(freq.argmax())] += room - int(freq.sum())
        while gap < 0:
            at = int(freq.argmax())
            take = min(-gap, int(freq[at]) // 2)
            freq[at] -= take
            gap += take
        return cls(freq)

    def symbols(self) -> np.ndarray:
        if self.slot is None:
            self.slot = np.repeat(np.arange(len(self.freq), dtype=np.uint32), self.freq.astype(np.int64))
        return self.slot


def encode(ids: np.ndarray, table: Table, lanes: int = LANES, every: int = EVERY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(words, states, places): the stream, and for each checkpoint the lanes' states and the place in it."""
    rows = -(-len(ids) // lanes)
    state = np.full(lanes, LOW, np.uint64)
    out: list[np.ndarray] = []
    written, marks, places = 0, [], []
    shift, scale = np.uint64(32), np.uint64(SCALE)
    for row in range(rows - 1, -1, -1):
        now = ids[row * lanes : (row + 1) * lanes]
        m = len(now)
        f, c, x = table.freq[now], table.start[now], state[:m]
        full = x >= (f << np.uint64(63 - SCALE))
        if full.any():
            words = x[full]
            out.append((words & np.uint64(0xFFFFFFFF)).astype(np.uint32)[::-1])
            written += len(words)
            x = np.where(full, x >> shift, x)
        q = x // f
        state[:m] = (q << scale) + (x - q * f) + c
        if row % every == 0:
            marks.append(state.copy())
            places.append(written)
    stream = np.concatenate(out)[::-1] if out else np.zeros(0, np.uint32)
    marks.reverse()
    places.reverse()
    return stream, np.array(marks, np.uint64).reshape(-1, lanes), written - np.array(places, np.int64)


def decode(words: np.ndarray, states: np.ndarray, places: np.ndarray, count: int, table: Table, every: int = EVERY, first: int = 0, last: int | None = None) -> np.ndarray:
    """The ids from checkpoint ``first`` up to checkpoint ``last`` (all by default)."""
    lanes = states.shape[1] if len(states) else LANES
    rows = -(-count // lanes)
    stop = rows if last is None else min(rows, last * every)
    if first * every >= stop:
        return np.zeros(0, np.uint32)
    slots, freq, start = table.symbols(), table.freq, table.start
    state, at = states[first].copy(), int(places[first])
    low, scale, shift = np.uint64((1 << SCALE) - 1), np.uint64(SCALE), np.uint64(32)
    out = np.empty(min(count, stop * lanes) - first * every * lanes, np.uint32)
    for row in range(first * every, stop):
        m = min(lanes, count - row * lanes)
        x = state[:m]
        slot = x & low
        s = slots[slot]
        out[(row - first * every) * lanes : (row - first * every) * lanes + m] = s
        x = freq[s] * (x >> scale) + slot - start[s]
        need = x < LOW
        k = int(need.sum())
        if k:
            x[need] = (x[need] << shift) | words[at : at + k].astype(np.uint64)
            at += k
        state[:m] = x
    return out


def pack(docs: np.ndarray, sizes: np.ndarray, ids: np.ndarray, table: Table) -> bytes:
    """Header of 8 little-endian words, documents' ids (null as the least long) and sizes, checkpoints, stream, crc32."""
    words, states, places = encode(ids, table)
    docs = np.asarray(docs, "<i8")
    body = b"".join([docs.tobytes(), np.asarray(sizes, "<u8").tobytes(), places.astype("<u8").tobytes(), states.astype("<u8").tobytes(), words.astype("<u4").tobytes()])
    head = np.array([len(docs), len(ids), states.shape[1], EVERY, len(states), len(words), zlib.crc32(np.asarray(ids, "<u4").tobytes()), zlib.crc32(table.freq.astype("<u4").tobytes())], "<u8").tobytes()
    return MAGIC + head + body + np.array([zlib.crc32(head + body)], "<u4").tobytes()


def unpack(data: bytes, table: Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Documents' ids, sizes and all token ids of a block; raises if a checksum differs."""
    if data[:8] != MAGIC or zlib.crc32(data[8:-4]) != int(np.frombuffer(data, "<u4", 1, len(data) - 4)[0]):
        raise ValueError("damaged block")
    n_docs, count, lanes, every, marks, n_words, crc, table_crc = (int(x) for x in np.frombuffer(data, "<u8", 8, 8))
    if table_crc != zlib.crc32(table.freq.astype("<u4").tobytes()):
        raise ValueError("block of another table")
    at = 72
    docs = np.frombuffer(data, "<i8", n_docs, at)
    sizes = np.frombuffer(data, "<u8", n_docs, at + 8 * n_docs).astype(np.int64)
    at += 16 * n_docs
    places = np.frombuffer(data, "<u8", marks, at).astype(np.int64)
    at += 8 * marks
    states = np.frombuffer(data, "<u8", marks * lanes, at).astype(np.uint64).reshape(-1, lanes)
    at += 8 * marks * lanes
    ids = decode(np.frombuffer(data, "<u4", n_words, at), states, places, count, table, every)
    if zlib.crc32(ids.astype("<u4").tobytes()) != crc:
        raise ValueError("damaged ids")
    return docs, sizes, ids


# --- on Spark --------------------------------------------------------------


def tokenized(docs: DataFrame, ranges: int, vocabulary: str, end_id: int | None, block: int) -> DataFrame:
    """Plain blocks: a range of documents is one task, sorted, so it knows the ids before each of its blocks.

    A task streams its range block by block, so its memory does not grow with the range.
    """
    shape = columns("part int, before long, n long, docs binary, sizes binary, ids binary, counts binary")

    def run(batches):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        encode_all = worker_encoder(vocabulary)
        part, before, docs, sizes, ids, end = None, 0, [], [], [], np.array([end_id or 0], np.uint16)

        def flush():
            every = np.concatenate(ids).astype("<u2")
            tally = np.bincount(every, minlength=1 << 16)
            seen = np.flatnonzero(tally)
            counts = np.stack([seen, tally[seen]], 1).astype("<u4").tobytes()
            ended = np.array([-(1 << 63) if d is None else d for d in docs], "<i8").tobytes()
            row = [part, before, len(every), ended, np.array(sizes, "<u8").tobytes(), every.tobytes(), counts]
            return pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip(row, shape)], schema=shape)

        for b in batches:
            for piece in slices(b, 1):
                got, lengths = encode_texts(piece.column(1), encode_all)
                at = 0
                for doc, p, n in zip(piece.column(0).to_pylist(), piece.column(2).to_pylist(), lengths.tolist()):
                    if docs and (p != part or sum_of(sizes) >= block):
                        yield flush()
                        before = before + sum_of(sizes) if p == part else 0
                        docs, sizes, ids = [], Sizes(), []
                    elif not docs:
                        sizes = Sizes()
                    part = p
                    mine = got[at : at + n]
                    at += n
                    docs.append(doc)
                    ids += [mine] if end_id is None else [mine, end]
                    sizes.append(n + (end_id is not None))
        if docs:
            yield flush()

    dealt = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange(ranges, "doc_id").sortWithinPartitions("doc_id", "text")
    return dealt.withColumn("part", F.spark_partition_id()).mapInArrow(lean(run, keep=vocabulary), "part int, before long, n long, docs binary, sizes binary, ids binary, counts binary")


class PieceEncoder:
    """Ids of distinct pieces through the tokenizer, remembered for up to ``limit`` of them.

    A piece is cut once more between a letter or digit and the punctuation that
    ends it, where pre-tokenisation always cuts, so words meet again whatever
    follows them. What is new goes through the tokenizer in long rows: every
    piece opens with the only space it has, so an id that opens with a space
    begins the next one.
    """

    def __init__(self, tok, limit: int = 1_500_000):
        self.fast, self.limit = getattr(tok, "encode_batch_fast", tok.encode_batch), limit
        self.opens = np.zeros(1 << 16, bool)
        for token, number in tok.get_vocab().items():
            self.opens[number] = token[0] == SPACE
        self.known = pa.array([], pa.string())
        self.ids, self.start, self.size = np.zeros(0, np.uint16), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def stems(self, new: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        rows = pc.binary_join(pa.ListArray.from_arrays(pa.array(np.append(np.arange(0, len(new), 100), len(new)), pa.int32()), pc.binary_join_element_wise("", new, " ")), "").to_pylist()
        ids, _ = laid_out([x.ids for x in self.fast(rows, add_special_tokens=False)])
        at = np.flatnonzero(self.opens[ids])
        if len(at) != len(new):
            raise ValueError("the vocabulary does not keep a leading space with its word")
        return ids, np.diff(np.append(at, len(ids)))

    def __call__(self, spaced: pa.Array, others: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        stem = pc.utf8_rtrim(spaced, characters=",.!?;:")
        whole = pc.invert(pc.match_substring_regex(stem, r"[\pL\pN]$"))
        stem = pc.if_else(whole, spaced, stem)
        stem, tail = stem.dictionary_encode(), self.tails(spaced, stem).dictionary_encode()
        found = pc.index_in(stem.dictionary, value_set=self.known)
        new = stem.dictionary.filter(found.is_null())
        ids, size = self.stems(new) if len(new) else (self.ids[:0], self.size[:0])
        rest, rest_size = laid_out([x.ids for x in self.fast(tail.dictionary.to_pylist() + others, add_special_tokens=False)])
        flat = np.concatenate([self.ids, ids, rest])
        start = np.concatenate([self.start, len(self.ids) + begins(size), len(self.ids) + len(ids) + begins(rest_size)])
        sizes = np.concatenate([self.size, size, rest_size])
        place = pc.fill_null(found, -1).to_numpy(zero_copy_only=False).astype(np.int64)
        place[place < 0] = len(self.known) + np.arange(len(new))
        base = len(self.known) + len(new)
        pair = np.stack([place[stem.indices.to_numpy(zero_copy_only=False)], base + tail.indices.to_numpy(zero_copy_only=False)], 1)
        joined = gather(flat, start[pair.ravel()], sizes[pair.ravel()])
        piece_size = sizes[pair].sum(1)
        last = base + len(tail.dictionary)
        other = gather(flat, start[last:], sizes[last:])
        if len(self.known) + len(new) <= self.limit:
            self.known = pa.concat_arrays([self.known, new])
            self.ids, self.start, self.size = np.concatenate([self.ids, ids]), start[:base], sizes[:base]
        every = np.concatenate([piece_size, sizes[last:]])
        return np.concatenate([joined, other]), begins(every), every

    @staticmethod
    def tails(spaced: pa.Array, stem: pa.Array) -> pa.Array:
        """What follows each stem."""
        size = pc.binary_length(spaced).to_numpy(zero_copy_only=False).astype(np.int64)
        cut = pc.binary_length(stem).to_numpy(zero_copy_only=False).astype(np.int64)
        data = np.frombuffer(b"".join(spaced.cast(pa.binary()).to_pylist()), np.uint8)
        left = gather(data, begins(size) + cut, size - cut)
        ends = np.concatenate([[0], np.cumsum(size - cut)]).astype(np.int32)
        return pa.StringArray.from_buffers(len(spaced), pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(left)))


def worker_encoder(vocabulary: str) -> PieceEncoder:
    """The encoder of a vocabulary, kept as long as the Python worker lives, over all tasks it runs."""
    import sys
    import types

    from tokenizers import Tokenizer

    kept = sys.modules.setdefault("tablemill_worker_cache", types.ModuleType("tablemill_worker_cache")).__dict__
    if vocabulary not in kept:
        kept[vocabulary] = PieceEncoder(Tokenizer.from_file(vocabulary))
    return kept[vocabulary]


class Sizes(list):
    """A list that knows its sum."""

    total = 0

    def append(self, x):
        self.total += x
        super().append(x)


def sum_of(sizes) -> int:
    return getattr(sizes, "total", 0)


def write(docs: DataFrame, path: str, vocabulary: str, end_id: int | None = END_ID, block: int = BLOCK, part_bytes: int = 24 << 20) -> None:
    """Encode ``docs`` into the files ``path/blocks`` and ``path/table``.

    Two passes: plain blocks by ranges of document id, with the counts of all
    their ids; then every plain block becomes a coded one, without a shuffle. What
    precedes a range is a table of at most ``RANGES`` rows that Spark sends along;
    the driver keeps one number for each id of the vocabulary.
    """
    spark = docs.sparkSession
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    ranges = max(spark.sparkContext.defaultParallelism, min(RANGES, -(-size // part_bytes)))
    plain = tokenized(docs, ranges, vocabulary, end_id, block)
    plain.write.option("compression", "zstd").parquet(f"{path}/plain")
    plain = spark.read.schema(plain.schema).parquet(f"{path}/plain")
    table = Table.of_counts(count_ids(plain))
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = plain.groupBy("part").agg(F.sum("n").alias("n")).select("part", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("offset"))
    coded(plain.join(F.broadcast(offsets), "part").withColumn("start", F.col("offset") + F.col("before")), table).write.option("compression", "uncompressed").parquet(f"{path}/blocks")
    spark.createDataFrame([(table.freq.astype("<u4").tobytes(),)], "freq binary").write.parquet(f"{path}/table")
    drop_path(spark, f"{path}/plain")


def count_ids(plain: DataFrame) -> np.ndarray:
    """Counts of all ids over all blocks."""
    shape = columns("id int, n long")

    def run(batches):
        tally = np.zeros(1 << 16, np.int64)
        for b in batches:
            for data in b.column(0).to_pylist():
                pairs = np.frombuffer(data, "<u4").reshape(-1, 2)
                tally[pairs[:, 0]] += pairs[:, 1]
        seen = np.flatnonzero(tally)
        yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int32()), pa.array(tally[seen])], schema=shape)

    counts = np.zeros(1 << 16, np.int64)
    for r in plain.select("counts").mapInArrow(lean(run), "id int, n long").groupBy("id").agg(F.sum("n").alias("n")).collect():
        counts[r.id] = r.n
    return counts


def coded(plain: DataFrame, table: Table) -> DataFrame:
    """(start, data): every plain block as a coded one."""
    freq = table.freq.astype(np.uint32)
    shape = columns("start long, data binary")

    def run(batches):
        coder = Table(freq)
        for b in batches:
            for start, docs, sizes, ids in zip(*b.columns):
                row = pack(np.frombuffer(docs.as_buffer(), "<i8"), np.frombuffer(sizes.as_buffer(), "<u8"), np.frombuffer(ids.as_buffer(), "<u2").astype(np.int64), coder)
                yield pa.RecordBatch.from_arrays([pa.array([start.as_py()], pa.int64()), pa.array([row], pa.binary())], schema=shape)

    return plain.select("start", "docs", "sizes", "ids").mapInArrow(lean(run), "start long, data binary")


def read(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids (32-bit little-endian) of every document of a file set."""
    shape = columns("doc_id long, start long, n_tokens long, ids_crc32 long")
    freq = np.frombuffer(bytes(spark.read.parquet(f"{path}/table").first().freq), "<u4")

    def run(batches):
        table = Table(freq)
        for b in batches:
            for start, data in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                docs, sizes, ids = unpack(data, table)
                plain, ends = ids.astype("<u4"), np.cumsum(sizes)
                crcs = [zlib.crc32(plain[e - n : e].tobytes()) for e, n in zip(ends.tolist(), sizes.tolist())]
                yield pa.RecordBatch.from_arrays([pa.array([None if d == -(1 << 63) else d for d in docs.tolist()], pa.int64()), pa.array(start + ends - sizes), pa.array(sizes), pa.array(crcs, pa.int64())], schema=shape)

    return spark.read.parquet(f"{path}/blocks").select("start", "data").mapInArrow(lean(run), "doc_id long, start long, n_tokens long, ids_crc32 long")


def op7_rans_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = work_path(spark, "token-ids")
    write(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), path, public_tokenizers.path("byte_bpe_50k.json"))
    return read(spark, path)
