"""Word-piece token counts by a linear longest-match automaton.

Greedy longest match from the left usually backtracks. A trie over the
vocabulary with failure links does not: when a byte cannot follow, the node's
link says where the remaining bytes stand, and its count says how many pieces
were completed on the way. Both are made once for the vocabulary, so the number
of pieces comes out in one pass without building a piece. The vocabulary must
hold all 256 bytes, so that every word can be cut.

A word is a run of non-white-space (ASCII white space), cut again into runs of
letters, digits and marks and single other characters; its first part carries
the leading space that word-initial entries have.

Defined results: null and empty texts have no words and no pieces; repeated
rows count alike; ``unknown`` is not needed as every byte is an entry.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablemill.llm.common import columns, lean, sums
from tablemill.llm.language import texts_words
from tablemill.llm.pieces import slices


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins that byte-level vocabularies use for the 256 bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


def read_vocabulary(path: str) -> list[bytes]:
    """Entries of a byte-level vocabulary file as bytes; named special tokens are left out."""
    with open(path, encoding="utf-8") as f:
        data = json.load(f)
    special = {t["content"] for t in data.get("added_tokens", [])}
    of = byte_alphabet()
    return [bytes(of[c] for c in token) for token in data["model"]["vocab"] if token not in special]


class Automaton:
    """Sorted transitions (node * 256 + byte), failure links and popped-piece counts."""

    def __init__(self, vocabulary: list[bytes]):
        child: list[dict[int, int]] = [{}]
        ends, depth, parent, via = [False], [0], [0], [0]
        for token in vocabulary:
            at = 0
            for byte in token:
                nxt = child[at].get(byte)
                if nxt is None:
                    nxt = child[at][byte] = len(child)
                    child.append({})
                    ends.append(False)
                    depth.append(depth[at] + 1)
                    parent.append(at)
                    via.append(byte)
                at = nxt
            ends[at] = True
        missing = [b for b in range(256) if b not in child[0] or not ends[child[0][b]]]
        if missing:
            raise ValueError(f"the vocabulary lacks {len(missing)} single bytes")
        fail, pops = [0] * len(child), [0] * len(child)
        for node in sorted(range(1, len(child)), key=depth.__getitem__):
            if ends[node]:
                pops[node] = 1  # the node's own text is a piece; nothing remains
                continue
            at, count = fail[parent[node]], pops[parent[node]]
            while via[node] not in child[at]:
                count += pops[at]
                at = fail[at]
            fail[node], pops[node] = child[at][via[node]], count
        pairs = sorted((n * 256 + b, c) for n, kids in enumerate(child) for b, c in kids.items())
        self.keys = np.array([k for k, _ in pairs], np.int64)
        self.next = np.array([c for _, c in pairs], np.int32)
        self.fail, self.pops = np.array(fail, np.int32), np.array(pops, np.int32)

    def counts(self, words: list[bytes]) -> np.ndarray:
        """Number of greedy pieces of each word; all words step together, longest first."""
        size = np.fromiter(map(len, words), np.int64, len(words))
        flat = np.frombuffer(b"".join(words), np.uint8)
        start = np.cumsum(size) - size
        order = np.argsort(-size, kind="stable")
        lengths = -size[order]
        node, total = np.zeros(len(words), np.int64), np.zeros(len(words), np.int64)
        for step in range(int(size.max(initial=0))):
            live = order[: int(np.searchsorted(lengths, -step, side="left"))]
            byte = flat[start[live] + step].astype(np.int64)
            todo = live
            while len(todo):
                key = node[todo] * 256 + byte
                at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
                ok = self.keys[at] == key
                node[todo[ok]] = self.next[at[ok]]
                todo, byte = todo[~ok], byte[~ok]
                total[todo] += self.pops[node[todo]]
                node[todo] = self.fail[node[todo]]
        todo = np.flatnonzero(node)
        while len(todo):
            total[todo] += self.pops[node[todo]]
            node[todo] = self.fail[node[todo]]
            todo = todo[node[todo] != 0]
        return total


def parts_of(word: str, cut) -> list[bytes]:
    found = cut(word)
    return [(" " + found[0]).encode(), *(p.encode() for p in found[1:])]


def counted(docs: DataFrame, vocabulary_path: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, n_chars, n_words, n_pieces, max_word_pieces of every whole text."""
    shape = columns("doc_id long, n_chars long, n_words long, n_pieces long, max_word_pieces long")

    def run(batches):
        import regex

        automaton, cut = None, regex.compile(r"[\p{L}\p{N}\p{M}]+|[^\p{L}\p{N}\p{M}]").findall
        for b in batches:
            automaton = automaton or Automaton(read_vocabulary(vocabulary_path))
            for part in slices(b, 1):
                pool, index, counts = texts_words(part.column(1))
                keep = np.fromiter(map(bool, (words := pool.to_pylist())), bool, len(pool))
                cuts = [parts_of(w, cut) if w else [] for w in words]
                sizes = np.fromiter(map(len, cuts), np.int64, len(cuts))
                pieces = sums(automaton.counts([p for c in cuts for p in c]), sizes)
                per = pieces[index]
                ends = np.cumsum(counts)
                most = [int(per[e - n : e].max(initial=0)) for e, n in zip(ends.tolist(), counts.tolist())]
                chars = [len(t or "") for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(chars, pa.int64()), pa.array(sums(keep[index].astype(np.int64), counts)), pa.array(sums(per, counts)), pa.array(most, pa.int64())], schema=shape)

    return docs.select(F.col(doc_id).cast("long"), F.col(text)).mapInArrow(lean(run), "doc_id long, n_chars long, n_words long, n_pieces long, max_word_pieces long")


def op5_wordpiece_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return counted(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.json"))
