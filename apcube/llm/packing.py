"""Best-fit-decreasing packing of tokenized documents into fixed-size sequences.

Piece lengths are whole numbers up to the capacity, so best-fit decreasing over *all* pieces is determined by the
histogram of lengths: ``plan`` runs it exactly on (length, count) pairs, moving runs of equal bins at once, with a
segment tree over remaining capacities that finds the tightest open bin in logarithmic time. The plan's size depends
on the capacity, not on the data. Executors then look up a piece's sequence by its rank among the pieces of its length;
ranks come from hashed sub-buckets of each length, so that the commonest length isn't ordered in one task.
"""

from __future__ import annotations

import json
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from apcube.llm.storage import materialize
from apcube.llm.wordhash import slices

#: Rows of a sub-bucket in which ranks are counted.
RANK_ROWS = 8_192
#: Blanks in a row from which on a text goes to the slower encoder.
BLANKS = 64
PIECES = "piece int, start bigint, length bigint, ids_crc32 bigint"

_LOADED: dict[str, object] = {}


def encoder(path: str):
    """A function from a text to its ids, those of the tokenizers library for the file at ``path`` (add_special_tokens
    False), loaded once per worker.

    Plain byte-level BPE, whose ids are ordered as its merges, is also read into tiktoken's encoder, several times as fast
    on prose: tests compare the two on every code point, on every entry and on random joints of entries. Texts for which
    that isn't so go to the library: those that hold a special token's string, and those with ``BLANKS`` blanks in a
    row, over which the other one runs out of stack. Files of another make go to the library alone.
    """
    if path not in _LOADED:
        import tokenizers

        library, spec = tokenizers.Tokenizer.from_file(path), json.loads(open(path, encoding="utf-8").read())
        special, blanks = [x["content"] for x in spec["added_tokens"]], re.compile(rf"\s{{{BLANKS}}}")
        fast = _ranked(path, spec)

        def encode(text: str) -> list[int]:
            if fast is None or any(x in text for x in special) or blanks.search(text):
                return library.encode(text, add_special_tokens=False).ids
            return fast.encode_ordinary(text)

        _LOADED[path] = encode
    return _LOADED[path]


def _ranked(path: str, spec: dict):
    """tiktoken's encoder over the entries of plain byte-level BPE; None for any other make."""
    import public_tokenizers
    import tiktoken

    model, before = spec["model"], spec.get("pre_tokenizer") or {}
    plain_make = model["type"] == "BPE" and not spec.get("normalizer") and before.get("type") == "ByteLevel" and before.get("use_regex", True) and not before.get("add_prefix_space")
    if not plain_make or any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "ignore_merges")):
        return None
    vocab = model["vocab"]
    merged = [vocab["".join(m) if isinstance(m, list) else m.replace(" ", "", 1)] for m in model["merges"]]
    if merged != sorted(merged):
        return None
    # Byte-level BPE writes the printable bytes as themselves and the others, ascending, from U+0100 on.
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [x for x in range(256) if x not in set(plain)]
    byte_of = {chr(x): x for x in plain} | {chr(256 + i): x for i, x in enumerate(rest)}
    special = {x["content"] for x in spec["added_tokens"]}
    ranks = {bytes(map(byte_of.__getitem__, token)): i for token, i in vocab.items() if token not in special}
    return tiktoken.Encoding(path, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def tokenize(docs: DataFrame, tokenizer: str, capacity: int, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """Rows (doc_id, piece, start, length, ids_crc32): each document's ids and ``end_id``, cut where longer than
    ``capacity`` into pieces of it, the first of which may be shorter."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        for part in slices(batches, "text", 8 << 20):
            rows: list[tuple[int, int, int, int, int]] = []
            for i, text in enumerate(part.column("text").to_pylist()):
                ids = np.array(encode(text or "") + [end_id], "<u4")
                first = len(ids) % capacity or capacity
                cuts = [0, *range(first, len(ids) + 1, capacity)]
                rows += [(i, k, a, b - a, zlib.crc32(ids[a:b])) for k, (a, b) in enumerate(zip(cuts, cuts[1:]))]
            at, piece, start, length, crc = (np.array(x) for x in zip(*rows))
            yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(at)), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))], ["doc_id", "piece", "start", "length", "ids_crc32"])

    narrow = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return narrow.mapInArrow(run, f"doc_id {narrow.schema['doc_id'].dataType.simpleString()}, {PIECES}")


class Capacities:
    """A segment tree over remaining capacities 0..capacity: which have open bins."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.open = [0] * (2 * self.size)

    def add(self, capacity: int, bins: int) -> None:
        i = capacity + self.size
        while i:
            self.open[i] += bins
            i >>= 1

    def tightest(self, need: int) -> int | None:
        """The least remaining capacity >= ``need`` that has an open bin."""
        i = need + self.size
        while not self.open[i]:
            while i & 1:  # a right child has nothing further right under its parent
                i >>= 1
            if not i:
                return None
            i += 1
        while i < self.size:
            i = 2 * i if self.open[2 * i] else 2 * i + 1
        return i - self.size


def plan(counts: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Best-fit decreasing over ``counts`` pieces of each length.

    Returns moves (length, first rank, number, first sequence, offset) - the pieces of a length with those ranks go, in
    order, to consecutive sequences at that offset - and the number of sequences. Pieces of one length fill a bin as
    often as they fit before another is touched, as the one-by-one method does, since what remains is then the tightest.
    """
    tree, groups, moves, bins = Capacities(capacity), defaultdict(list), [], 0

    def push(rest: int, first: int, number: int) -> None:
        if rest and number:
            groups[rest].append((first, number))
            tree.add(rest, number)

    for length in sorted((x for x in counts if counts[x]), reverse=True):
        left, rank = counts[length], 0
        while left:
            rest = tree.tightest(length)
            if rest is None:
                rest = capacity
                first, number = bins, -(-left // (capacity // length))
                bins += number
            else:
                first, number = groups[rest].pop()
                tree.add(rest, -number)
            each = rest // length
            full = min(number, left // each)
            for s in range(each if full else 0):
                moves.append((length, rank, full, first, capacity - rest + s * length))
                rank += full
            left -= full * each
            push(rest - each * length, first, full)
            if left and full < number:
                for s in range(left):
                    moves.append((length, rank, 1, first + full, capacity - rest + s * length))
                    rank += 1
                push(rest - left * length, first + full, 1)
                left, full = 0, full + 1
            push(rest, first + full, number - full)
    return moves, bins


def pack(docs: DataFrame, tokenizer: str, capacity: int = 1024, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, piece int, start, length, ids_crc32, sequence_id, offset (all long).

    A null text is an empty one, whose only id is ``end_id``; a text of any length is encoded whole, and a special token's
    string in it is that token. Rows with equal or null ids are packed like others. Equal
    lengths are told apart by (doc_id, piece); rows equal in both may swap places. Other columns are ignored. An empty
    table gives no rows. Sequences are gapless from offset 0.
    """
    pieces = materialize(tokenize(docs, tokenizer, capacity, end_id, id_col, text_col), "pieces")
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    moves, _ = plan(counts, capacity)
    moves.sort()
    table = np.array(moves or [(0, 0, 0, 0, 0)], np.int64)
    begin = np.searchsorted(table[:, 0], np.arange(capacity + 2))
    shared = docs.sparkSession.sparkContext.broadcast((table, begin))
    buckets = max(1, -(-sum(counts.values()) // RANK_ROWS))
    dealt = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(buckets)))
    sizes = dealt.groupBy("length", "bucket").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("length", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    within = Window.partitionBy("length", "bucket").orderBy("doc_id", "piece")
    ranked = dealt.withColumn("rank", F.row_number().over(within)).join(sizes, ["length", "bucket"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("rank") - 1 + F.col("before")).alias("rank"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, begin = shared.value
        for x in batches:
            length, rank = (x.column(c).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            at = np.empty(len(rank), np.int64)
            for v in np.unique(length):
                rows = np.flatnonzero(length == v)
                lo, hi = begin[v], begin[v + 1]
                at[rows] = lo + np.searchsorted(table[lo:hi, 1], rank[rows], side="right") - 1
            move = table[at]
            yield pa.RecordBatch.from_arrays([*(x.column(i) for i in range(5)), pa.array(move[:, 3] + rank - move[:, 1]), pa.array(move[:, 4])], [*x.schema.names[:5], "sequence_id", "offset"])

    return ranked.mapInArrow(run, f"doc_id {pieces.schema['doc_id'].dataType.simpleString()}, {PIECES}, sequence_id bigint, offset bigint")
