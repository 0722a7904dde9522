"""Byte-level BPE by ranks, encoded and decoded with DuckDB inside each task.

Encoding: the distinct pre-tokens of a slice become rows (word, position, id),
one a byte. A recursive query joins neighbours with the merge table (all ways
to split a vocabulary entry into two others, with its rank), takes each word's
minimum of (rank, position), contracts that pair and renumbers, until no pair of
the word can merge. A query runs at most ``TURNS`` rounds and hands over what
is unfinished to the next one; words are dealt to queries so that rows times
rounds stay within ``HISTORY``. Pre-tokens that are vocabulary entries need no merge.

A pre-token of more than ``LONG`` bytes is first cut wherever no vocabulary entry
spans the cut: every token is a vocabulary entry, so none can ever lie across it
and both sides merge alone. A stretch that stays longer is contracted in arrays
by the same rule, the non-overlapping places of the minimum pair in one round, up
to the first that opens a pair of a lower rank, just as one place after the other
would. So neither the length of a text nor that of a word without a break bounds
what can be encoded: memory is linear in the longest word.

Decoding: token rows join the vocabulary's bytes, and an ordered aggregate
strings them together by document.

Defined results: null and empty texts have no ids; repeated rows are encoded
alike; a null document id passes through.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablemill.llm.common import columns, lean, sums
from tablemill.llm.pieces import begins, encode_texts, gather, slices

TURNS = 64
LONG = 256
CHUNK = 20_000  # words of one query
HISTORY = 8_000_000  # rows times rounds of one query
CACHE = 100_000  # words of one generation; two of them, and those of a slice, are remembered
MEMORY = "128MB"
NONE = np.int64(1 << 40)

MERGE_SQL = f"""
WITH RECURSIVE step(turn, w, pos, id) AS (
  SELECT 0, w, pos, id FROM start
  UNION ALL
  (WITH best AS (
     SELECT a.w, min(m.id::BIGINT * 4294967296 + a.pos) AS hit
     FROM step a JOIN step b ON b.w = a.w AND b.pos = a.pos + 1
     JOIN merges m ON m.pair = a.id::BIGINT * 65536 + b.id
     GROUP BY a.w)
   SELECT turn + 1, w, pos - (pos > hit % 4294967296)::INT,
          CASE WHEN pos = hit % 4294967296 THEN (hit // 4294967296)::INT ELSE id END
   FROM step JOIN best USING (w)
   WHERE turn < {TURNS} AND pos <> hit % 4294967296 + 1))
SELECT w, max(turn) AS turn, list(id ORDER BY pos) AS ids
FROM step SEMI JOIN (SELECT w, max(turn) AS turn FROM step GROUP BY w) USING (w, turn)
GROUP BY w ORDER BY w
"""

DECODE_SQL = "SELECT doc, list(bytes ORDER BY pos) AS parts FROM tokens JOIN vocabulary USING (id) GROUP BY doc ORDER BY doc"


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


class Coder:
    """Ranks and pattern in a DuckDB connection of one task."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, memory: str = MEMORY):
        import duckdb
        import regex

        self.ranks, self.cut = ranks, regex.compile(pattern).findall
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.spans = None
        self.bytes = np.zeros(256, np.int32)
        for token, rank in ranks.items():
            if len(token) == 1:
                self.bytes[token[0]] = rank
        merges = [(ranks[t[:i]] * 65536 + ranks[t[i:]], r) for t, r in ranks.items() for i in range(1, len(t)) if t[:i] in ranks and t[i:] in ranks]
        pair, made = np.array([p for p, _ in merges], np.int64), np.array([r for _, r in merges], np.int64)
        order = np.argsort(pair)
        self.pair, self.made = pair[order], made[order]
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": memory, "temp_directory": "", "preserve_insertion_order": "false"})
        given = pa.table({"pair": pair, "id": made.astype(np.int32)})  # noqa: F841
        self.db.execute("CREATE TABLE merges AS SELECT * FROM given")
        given = pa.table({"id": pa.array(list(ranks.values()), pa.int32()), "bytes": pa.array(list(ranks), pa.binary())})  # noqa: F841
        self.db.execute("CREATE TABLE vocabulary AS SELECT * FROM given")

    def merge(self, words: list[bytes]) -> list[bytes]:
        """Ids of each word, as 16-bit little-endian bytes."""
        if not words:
            return []
        size = np.fromiter(map(len, words), np.int64, len(words))
        ids = self.bytes[np.frombuffer(b"".join(words), np.uint8)]
        out: list[bytes] = [b""] * len(words)
        left = np.arange(len(words))
        while len(left):
            of = np.repeat(left, size)
            pos = np.arange(len(ids)) - np.repeat(np.cumsum(size) - size, size)
            start = pa.table({"w": pa.array(of, pa.int32()), "pos": pa.array(pos, pa.int32()), "id": pa.array(ids, pa.int32())})  # noqa: F841
            got = self.db.sql(MERGE_SQL).to_arrow_table().combine_chunks()
            w, turn = got.column("w").to_numpy(), got.column("turn").to_numpy()
            lists = got.column("ids").chunk(0)
            ends = lists.offsets.to_numpy().astype(np.int64)
            flat = lists.values.to_numpy()
            data = flat.astype("<u2").tobytes()
            ended = turn < TURNS
            for i, a, b, done in zip(w.tolist(), (2 * ends[:-1]).tolist(), (2 * ends[1:]).tolist(), ended.tolist()):
                if done:
                    out[i] = data[a:b]
            left, size = w[~ended].astype(np.int64), np.diff(ends)[~ended]
            ids = gather(flat, ends[:-1][~ended], size)
        return out

    def merge_all(self, words: list[bytes]) -> list[bytes]:
        """Ids of words of any length; a query holds as many words as its history has room for."""
        out: list[bytes] = []
        at = 0
        while at < len(words):
            longest = len(words[at])  # words come longest first
            end = at + max(1, min(CHUNK, HISTORY // (longest * min(longest, TURNS))))
            out += self.merge(words[at:end])
            at = end
        return out

    def stretches(self, word: bytes) -> list[bytes]:
        """``word`` cut wherever no vocabulary entry spans the cut."""
        import ahocorasick

        if self.spans is None:
            self.spans = ahocorasick.Automaton()
            for token in self.ranks:
                if len(token) > 1:
                    self.spans.add_word(token.decode("latin-1"), len(token))
            self.spans.make_automaton()
        cover = np.zeros(len(word) + 1, np.int32)  # +1 where a span opens, -1 where it closes
        for last, n in self.spans.iter(word.decode("latin-1")):
            cover[last - n + 2] += 1
            cover[last + 1] -= 1
        cuts = np.flatnonzero(np.cumsum(cover)[1 : len(word)] == 0) + 1
        ends = [0, *cuts.tolist(), len(word)]
        return [word[a:b] for a, b in zip(ends, ends[1:])]

    def ranks_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left * 65536 + right
        at = np.minimum(np.searchsorted(self.pair, key), len(self.pair) - 1)
        return np.where(self.pair[at] == key, self.made[at], NONE) if len(self.pair) else np.full(len(key), NONE)

    def contracted(self, word: bytes) -> bytes:
        """Ids of one long stretch: the minimum pair's places are contracted together."""
        ids = self.bytes[np.frombuffer(word, np.uint8)].astype(np.int64)
        rank = np.append(self.ranks_of(ids[:-1], ids[1:]), NONE)
        while (low := int(rank.min())) < NONE:
            hit = np.flatnonzero(rank == low)
            opens = np.diff(hit, prepend=-2) != 1
            hit = hit[(hit - hit[opens][np.cumsum(opens) - 1]) % 2 == 0]  # of places that overlap in a row, every other one from the left
            # What stands beside each new token when its turn comes.
            before = np.where(np.diff(hit, prepend=-2) == 2, low, ids[hit - 1])
            after = ids[np.minimum(hit + 2, len(ids) - 1)]
            lower = (self.ranks_of(before, np.full(len(hit), low)) < low) & (hit > 0)
            lower |= (self.ranks_of(np.full(len(hit), low), after) < low) & (hit + 2 < len(ids))
            if lower.any():
                hit = hit[: int(lower.argmax()) + 1]
            ids[hit] = low
            keep = np.ones(len(ids), bool)
            keep[hit + 1] = False
            ids, rank = ids[keep], rank[keep]
            new = hit - np.arange(len(hit))
            for at in (new, new[new > 0] - 1):
                inner = at[at + 1 < len(ids)]
                rank[at] = NONE
                rank[inner] = self.ranks_of(ids[inner], ids[inner + 1])
        return ids.astype("<u2").tobytes()

    def learn(self, words: list[str], known: dict[str, bytes]) -> None:
        """Add the ids of new words to ``known``."""
        short: dict[bytes, bytes] = {}
        parts: dict[str, list[bytes]] = {}
        mine: list[tuple[str, bytes]] = []
        for w in words:
            data = w.encode()
            rank = self.ranks.get(data)
            if rank is not None:
                known[w] = rank.to_bytes(2, "little")
            elif len(data) <= LONG:
                short[data] = b""
                mine.append((w, data))
            else:
                parts[w] = self.stretches(data)
        long: dict[bytes, bytes] = {}
        for x in {x for p in parts.values() for x in p}:
            if x in self.ranks:
                long[x] = self.ranks[x].to_bytes(2, "little")
            elif len(x) > LONG:
                long[x] = self.contracted(x)
            else:
                short[x] = b""
        # Words of a like length together: a recursion takes as many rounds as its longest word.
        order = sorted(short, key=len, reverse=True)
        short = dict(zip(order, self.merge_all(order)))
        known.update((w, short[data]) for w, data in mine)
        for w, p in parts.items():
            known[w] = b"".join([long[x] if x in long else short[x] for x in p])

    def encode(self, spaced: pa.Array, others: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of each distinct string: its pre-tokens, each merged separately.

        Words are remembered in two generations: one met again moves to the younger,
        and when that is full the older is forgotten. So frequent words stay known
        however many rare ones pass by.
        """
        # Pre-tokens are kept as numbers: as strings, those of a slice would take most of a worker's memory.
        index: dict[str, int] = {}
        numbers, counts = array("i"), array("i")
        for s in chain((" " + s.as_py() for s in spaced), others):
            words = self.cut(s)
            counts.append(len(words))
            numbers.extend([index.setdefault(w, len(index)) for w in words])
        known, older = self.known, self.older
        new = []
        for w in index:
            if w not in known:
                if (ids := older.get(w)) is None:
                    new.append(w)
                else:
                    known[w] = ids
        self.learn(new, known)
        each = [known[w] for w in index]
        size = np.fromiter(map(len, each), np.int64, len(each)) // 2
        number = np.frombuffer(numbers, np.int32)
        flat = gather(np.frombuffer(b"".join(each), "<u2"), begins(size)[number], size[number])
        sizes = sums(size[number], np.frombuffer(counts, np.int32))
        # What is remembered is bounded in words and, by leaving long ones out, in bytes.
        for w in new:
            if len(w) > LONG:
                del known[w]
        if len(known) > CACHE:
            self.known, self.older = {}, known
        return flat, begins(sizes), sizes

    def decode(self, ids: np.ndarray, sizes: np.ndarray, rows: int = 200_000) -> list[bytes]:
        """The bytes of each document's ids; a query takes about ``rows`` of them, a longer document in parts."""
        out = [b""] * len(sizes)
        of = np.repeat(np.arange(len(sizes), dtype=np.int32), sizes)
        for at in range(0, len(ids), rows):
            part = ids[at : at + rows]
            tokens = pa.table({"doc": of[at : at + rows], "pos": np.arange(len(part), dtype=np.int32), "id": part.astype(np.int32)})  # noqa: F841
            got = self.db.sql(DECODE_SQL).to_arrow_table().combine_chunks()
            lists = got.column("parts").chunk(0)
            pieces = lists.values
            cuts, data = np.frombuffer(pieces.buffers()[1], np.int32 if pa.types.is_binary(pieces.type) or pa.types.is_string(pieces.type) else np.int64), memoryview(pieces.buffers()[2])
            ends = cuts[pieces.offset + lists.offsets.to_numpy().astype(np.int64)].tolist()
            for doc, a, b in zip(got.column("doc").to_pylist(), ends, ends[1:]):
                out[doc] += bytes(data[a:b])
        return out


def worker_coder(ranks_path: str, pattern: str) -> Coder:
    """The coder of a rank file, kept by the Python worker until it runs a task of another operator."""
    import sys
    import types

    kept = sys.modules.setdefault("tablemill_worker_cache", types.ModuleType("tablemill_worker_cache")).__dict__
    if (key := f"ranks {ranks_path} {pattern}") not in kept:
        kept[key] = Coder(read_ranks(ranks_path), pattern)
    return kept[key]


def encoded(docs: DataFrame, ranks_path: str, pattern: str, text: str = "text", doc_id: str = "doc_id", fn=None, returns: str | None = None) -> DataFrame:
    """(doc_id, ids, decoded): 32-bit little-endian ids of each whole text, and the bytes decoded from them.

    ``fn(doc ids, id bytes, decoded bytes) -> arrays`` may replace the two long columns by others.
    """
    returns = returns or "doc_id long, ids binary, decoded binary"
    shape = columns(returns)

    def run(batches):
        coder = None
        for b in batches:
            coder = coder or worker_coder(ranks_path, pattern)
            for part in slices(b, 1, 4 << 20):
                flat, sizes = encode_texts(part.column(1), coder.encode)
                ends = np.cumsum(sizes)
                wide = flat.astype("<u4")
                ids = [wide[e - n : e].tobytes() for e, n in zip(ends.tolist(), sizes.tolist())]
                texts = coder.decode(flat, sizes)
                arrays = [part.column(0), *(fn(ids, texts) if fn else (pa.array(ids, pa.binary()), pa.array(texts, pa.binary())))]
                yield pa.RecordBatch.from_arrays(arrays, schema=shape)

    return docs.select(F.col(doc_id).cast("long"), F.col(text)).mapInArrow(lean(run, keep="ranks"), returns)


def digests(ids: list[bytes], texts: list[bytes]) -> tuple[pa.Array, ...]:
    return pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in ids]), pa.array([hashlib.sha256(x).hexdigest() for x in texts])


def digest(docs: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    return encoded(docs, ranks_path, pattern, fn=digests, returns="doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op10_duckdb_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return digest(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
