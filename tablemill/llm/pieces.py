"""Encode whole texts through the distinct pieces of an Arrow batch.

Byte-level pre-tokenisation never joins characters across a lone space between
two non-blank characters: the space opens the next pre-token. A text may
therefore be cut before every such space and its pieces encoded on their own.
Pieces repeat heavily, so only the distinct ones of a batch are encoded. A text
whose spaces touch other white space is not cut there but encoded whole.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


Encode = Callable[[pa.Array, list[str]], tuple[np.ndarray, np.ndarray, np.ndarray]]


def encode_texts(texts: pa.Array, encode: Encode) -> tuple[np.ndarray, np.ndarray]:
    """All ids, text after text, and the number of ids of each text.

    ``encode(pieces, others)`` gets distinct pieces, each to be encoded with a space
    before it, and further strings; it returns an array of ids and, for all of them
    in this order, where their ids begin and how many they are. Null counts as empty.
    """
    texts = pc.fill_null(texts.cast(pa.string()), "")
    n = len(texts)
    if not n:
        return np.zeros(0, np.uint16), np.zeros(0, np.int64)
    parts = pc.split_pattern(texts, " ")
    offsets = parts.offsets.to_numpy().astype(np.int64)
    offsets -= offsets[0]
    coded = parts.flatten().dictionary_encode()
    index, pool = coded.indices.to_numpy(zero_copy_only=False), coded.dictionary
    # A piece that is empty or begins or ends with white space touches a space; only a text of one piece has none.
    odd = pc.or_(pc.equal(pool, ""), pc.not_equal(pool, pc.utf8_trim_whitespace(pool))).to_numpy(zero_copy_only=False)
    counts, first = np.diff(offsets), offsets[:-1]
    bad = np.add.reduceat(odd[index], first) > 0
    bad |= counts == 1
    inner = ~np.repeat(bad, counts)
    inner[first] = False
    used = np.zeros(len(pool), bool)
    used[index[inner]] = True
    spaced = np.flatnonzero(used)
    heads, head_code = np.unique(index[first[~bad]], return_inverse=True)
    others = pool.take(pa.array(heads)).to_pylist() + texts.take(pa.array(np.flatnonzero(bad))).to_pylist()
    flat, start, size = encode(pool.take(pa.array(spaced)), others)
    # One code for each kept piece, in text order.
    code_of = np.zeros(len(pool), np.int32)
    code_of[spaced] = np.arange(len(spaced))
    codes = code_of[index]
    codes[first[~bad]] = len(spaced) + head_code
    codes[first[bad]] = len(spaced) + len(heads) + np.arange(int(bad.sum()))
    inner[first] = True
    codes = codes[inner]
    per_piece = size[codes]
    out = gather(flat, start[codes], per_piece)
    per_text = np.where(bad, 1, counts)
    ends = np.cumsum(per_text)
    running = np.concatenate([[0], np.cumsum(per_piece)])
    return out, running[ends] - running[ends - per_text]


def laid_out(lists: list) -> tuple[np.ndarray, np.ndarray]:
    """Lists of ids as one array and their sizes."""
    size = np.fromiter(map(len, lists), np.int64, len(lists))
    return np.fromiter(chain.from_iterable(lists), np.uint16, int(size.sum())), size


def gather(flat: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Concatenate ``flat[start:start + size]`` of all rows."""
    total = int(sizes.sum())
    if not total:
        return flat[:0]
    ends = np.cumsum(sizes)
    at = np.arange(total) + np.repeat(starts - (ends - sizes), sizes)
    return flat[at]


def begins(sizes: np.ndarray) -> np.ndarray:
    return np.cumsum(sizes) - sizes


def slices(batch: pa.RecordBatch, column: int, budget: int = 8 << 20, rows: int = 4000):
    """Cut a batch so that the texts of a slice stay near ``budget`` bytes (one long text may exceed it)."""
    size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).cumsum()
    at = 0
    while at < batch.num_rows:
        base = size[at - 1] if at else 0
        end = int(np.searchsorted(size, base + budget, side="right"))
        end = min(max(end, at + 1), at + rows, batch.num_rows)
        yield batch.slice(at, end - at)
        at = end
