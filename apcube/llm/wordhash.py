"""Words of Arrow text columns as 64-bit hashes, in numpy over whole batches.

A word is a maximal run of bytes other than space and 0x09-0x0D. Those bytes never occur inside a multi-byte UTF-8
sequence, so splitting bytes equals splitting characters. The hash of a word is a polynomial over its (A-Z
lower-cased) bytes modulo 2**64 in an odd base, taken from differences of a running sum and then mixed; no Python
object is made per word. Texts are handled whole: a slice ends between documents, never inside one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

BASE = np.uint64(0x9E3779B97F4A7C15)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_POW = [np.ones(1, np.uint64), np.ones(1, np.uint64)]
_INV = np.uint64(pow(int(BASE), -1, 1 << 64))

_TABLE = np.arange(256, dtype=np.uint8)
_TABLE[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = x ^ (x >> np.uint64(30))
    x *= _M1
    x ^= x >> np.uint64(27)
    x *= _M2
    x ^= x >> np.uint64(31)
    return x


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POW[0]) < n:
        for k, base in enumerate((BASE, _INV)):
            p = np.full(max(n, 1 << 16), base, np.uint64)
            p[0] = 1
            _POW[k] = np.multiply.accumulate(p)
    return _POW[0][:n], _POW[1][:n]


@dataclass
class Words:
    """Words of a run of documents. ``hash[bounds[i]:bounds[i+1]]`` are those of document i in order."""

    hash: np.ndarray
    bounds: np.ndarray

    @property
    def per_doc(self) -> np.ndarray:
        return np.diff(self.bounds)


def hash_words(data: np.ndarray, offsets: np.ndarray) -> Words:
    """``data``: the UTF-8 bytes of all documents; ``offsets``: where each begins, and the end."""
    base = int(offsets[0])
    data, offsets = data[base : int(offsets[-1])], offsets.astype(np.int64) - base
    n = len(data)
    if not n:
        return Words(np.empty(0, np.uint64), np.zeros(len(offsets), np.int64))
    word = ~_SPACE[data]
    begin = word.copy()
    begin[1:] &= ~word[:-1]
    cut = offsets[1:-1]
    cut = cut[cut < n]
    begin[cut] = word[cut]
    starts = np.flatnonzero(begin)
    last = word.copy()
    last[:-1] &= ~word[1:]
    before = cut[cut > 0] - 1
    last[before] = word[before]
    ends = np.flatnonzero(last) + 1
    out = np.empty(len(starts), np.uint64)
    block = 1 << 18
    firsts = np.searchsorted(starts, np.arange(0, n, block))
    firsts = np.append(firsts, len(starts))
    for a, b in zip(firsts[:-1], firsts[1:]):  # running sums over pieces that stay in cache
        if a == b:
            continue
        lo, hi = int(starts[a]), int(ends[b - 1])
        up, down = _powers(hi - lo + 1)
        run = np.zeros(hi - lo + 1, np.uint64)
        np.cumsum((_TABLE[data[lo:hi]].astype(np.uint64) + np.uint64(1)) * up[:-1], out=run[1:])
        s, e = starts[a:b] - lo, ends[a:b] - lo
        out[a:b] = (run[e] - run[s]) * down[s] + (e - s).astype(np.uint64) * _M1
    return Words(mix(out), np.searchsorted(starts, offsets))


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null is an empty text."""
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    data = column.buffers()[2]
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8), offsets


def slices(batches: Iterator[pa.RecordBatch], text: str = "text", most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Batches of about ``most`` bytes of text; a longer document comes alone."""
    for batch in batches:
        if not batch.num_rows:
            continue
        _, offsets = text_buffers(batch.column(text))
        at = 0
        while at < batch.num_rows:
            to = int(np.searchsorted(offsets, offsets[at] + most, side="right")) - 1
            to = min(max(to, at + 1), batch.num_rows)
            yield batch.slice(at, to - at)
            at = to


def shingle_hashes(words: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the runs of ``k`` words, document by document, and their bounds; a document of 1 to k-1 words has its
    whole sequence as its one shingle, one without words none."""
    n = words.per_doc
    count = np.where(n >= k, n - k + 1, (n > 0).astype(np.int64))
    bounds = np.concatenate([[0], np.cumsum(count)])
    h = words.hash
    total = int(bounds[-1])
    if not total:
        return np.empty(0, np.uint64), bounds
    doc = np.repeat(np.arange(len(n)), count)
    at = np.arange(total) - bounds[doc] + words.bounds[doc]
    end = words.bounds[doc + 1]
    out = np.zeros(total, np.uint64)
    factor = int(BASE)
    for i in range(k):
        inside = at + i < end
        out[inside] += mix(h[at[inside] + i] ^ np.uint64(i + 1)) * np.uint64(factor)
        factor = factor * int(_M2) % (1 << 64)
    return mix(out), bounds


def distinct_per_doc(values: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values of each document, ascending, and their bounds."""
    if not len(values):
        return values, bounds
    v = values.copy()
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
        v[a:b].sort()
    keep = np.ones(len(v), bool)
    keep[1:] = v[1:] != v[:-1]
    keep[bounds[:-1][bounds[:-1] < len(v)]] = True
    return v[keep], np.concatenate([[0], np.cumsum(keep)])[bounds]
