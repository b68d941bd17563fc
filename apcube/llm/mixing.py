"""Mixing sources to target weights by Sainte-Lague apportionment of equal-token blocks.

1. Words per source are summed (partial aggregation; one row per source reaches the driver).
2. Targets: the sources share the total by weight; a target stops at ``most_repeats`` times its source, and the excess
   is shared again by weight until none is above.
3. Blocks of ``block`` words go to sources by highest quotients target / (2 seats + 1). That rule is house-monotone, so
   the seats after each output shard's last block are nested and their differences are whole quotas per shard.
4. Within a source, documents stand in a seeded hash order and are cut into blocks, whose order in turn is a seeded
   permutation of the source's blocks. Each shard takes its quota of the next blocks of every source in that order,
   which begins again where the quotas exceed the source; the last block is taken in part where the source's last block
   is a short one. Where a block stands in the permutation is a closed form: no block is ever made into a row. Places of
   documents come from hashed sub-buckets and their offsets, so a source that holds a third of all rows is not ordered
   in one task.
"""

from __future__ import annotations

import heapq
import math
import zlib
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from apcube.llm.storage import materialize

WORD = r"[^\x20\x09-\x0D]+"
#: Rows of a sub-bucket in which documents are ordered.
ORDER_ROWS = 8_192
#: More sources than this are refused: their totals are held by the driver.
MOST_SOURCES = 1_000_000
#: Words of an output shard; shards are larger where the table of quotas (shards times sources, broadcast) would have more
#: than MOST_QUOTAS entries.
SHARD_WORDS, MOST_QUOTAS = 1 << 22, 1 << 21


def targets(sizes: Sequence[int], weights: Sequence[float], most_repeats: int = 3, share: float = 1.0) -> list[float]:
    """Water-filling of ``share`` of all sizes by weight under caps ``most_repeats`` * size."""
    size, weight = np.array(sizes, float), np.array(weights, float)
    out, live = np.zeros(len(size)), np.ones(len(size), bool)
    left = share * size.sum()
    while live.any() and left > 0:
        give = np.where(live, weight * left / weight[live].sum(), 0)
        over = live & (give > most_repeats * size)
        if not over.any():
            out[live] = give[live]
            break
        out[over] = most_repeats * size[over]
        left -= out[over].sum()
        live &= ~over
    return out.tolist()


def apportion(wants: Sequence[float], seats: int) -> list[int]:
    """Seats by highest quotients want / (2 s + 1), ties to the earlier. It starts two below each proportional share
    (none can end lower than that by more than the loop repairs, see the check) and hands out the rest one by one."""
    total = sum(wants)
    if not total or seats <= 0:
        return [0] * len(wants)
    slack = 2
    while True:
        got = [max(0, int(w * seats / total) - slack) for w in wants]
        heap = [(-w / (2 * s + 1), i) for i, (w, s) in enumerate(zip(wants, got)) if w > 0]
        heapq.heapify(heap)
        for _ in range(seats - sum(got)):
            _, i = heap[0]
            got[i] += 1
            heapq.heapreplace(heap, (-wants[i] / (2 * got[i] + 1), i))
        last = min((w / (2 * s - 1) for w, s in zip(wants, got) if s), default=0)
        if -heap[0][0] <= last * (1 + 1e-12) or slack > seats:
            return got
        slack *= 4


def shard_quotas(wants: Sequence[float], seats: int, shards: int) -> list[list[int]]:
    """Per shard, the blocks of each source; every shard has ``seats / shards`` blocks, to within one."""
    seen, out = [0] * len(wants), []
    for k in range(shards):
        now = apportion(wants, seats * (k + 1) // shards)
        out.append([b - a for a, b in zip(seen, now)])
        seen = now
    return out


@dataclass
class Walk:
    """The blocks of a source in their seeded order, and what the shards take of them."""

    size: int
    block: int
    quota: int
    """Words taken of the source."""
    ends: np.ndarray
    """Blocks taken up to each shard's end."""
    seed: str

    def __post_init__(self):
        self.blocks = max(1, -(-self.size // self.block))
        # a step without a common divisor makes the order a permutation; it is short, so that products stay in 64 bits
        self.step = max(1, round(0.618 * min(self.blocks, 1 << 20)))
        while math.gcd(self.step, self.blocks) > 1:
            self.step += 1
        self.first = zlib.crc32(self.seed.encode()) % self.blocks
        self.rounds, rest = divmod(self.quota, self.size) if self.size else (0, 0)
        short = self.size - self.block * (self.blocks - 1)
        at = int(self.place(np.array([self.blocks - 1]))[0])  # where the short block stands
        if rest <= self.block * at:
            self.whole, self.part = divmod(rest, self.block)
        elif rest < self.block * at + short:
            self.whole, self.part = at, rest - self.block * at
        else:
            self.whole, self.part = divmod(rest + self.block - short, self.block)

    def place(self, number: np.ndarray) -> np.ndarray:
        """Where blocks stand in the order."""
        return (number * self.step + self.first) % self.blocks

    def take(self, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """start, size: words of documents on the source -> (document, shard, words), one row per pair that has words."""
        last = np.where(size > 0, (start + size - 1) // self.block, start // self.block - 1)
        n = last - start // self.block + 1
        doc = np.repeat(np.arange(len(start)), n)
        number = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(start // self.block, n)
        lo = np.maximum(start[doc], number * self.block)
        hi = np.minimum((start + size)[doc], (number + 1) * self.block)
        at = self.place(number)
        docs, shards, words = [], [], []
        for turn in range(self.rounds + 1):
            w = hi - lo
            if turn == self.rounds:
                w = np.where(at < self.whole, w, np.where(at == self.whole, np.clip(number * self.block + self.part - lo, 0, w), 0))
            some = np.flatnonzero(w)
            docs.append(doc[some])
            shards.append(np.minimum(np.searchsorted(self.ends, turn * self.blocks + at[some], side="right"), len(self.ends) - 1))
            words.append(w[some])
        key, back = np.unique(np.concatenate(docs) * len(self.ends) + np.concatenate(shards), return_inverse=True)
        return key // len(self.ends), key % len(self.ends), np.bincount(back, np.concatenate(words), len(key)).astype(np.int64)


TAKEN = "doc_id, size, source_size, target, taken, shards"


def mix(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), most_repeats: int = 3, share: float = 1.0, block: int = 64, seed: int = 7, shard_words: int = SHARD_WORDS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", carry: bool = False) -> DataFrame:
    """Per row of ``docs``: doc_id, size, source_size long, target double, taken long, shards array of (shard int, words
    long); with ``carry`` also row, a struct of all columns of ``docs``.

    ``size`` counts words (null or empty text: 0, taken 0). Sources in code-point order, a null source last and one of
    its own, get the ``weights`` in turn. A source's taken words differ from its target by about one block; no document
    gives more than ``most_repeats`` times its size. ``shards`` tells which output shards take how many of the document's
    words; every shard has about ``shard_words``, shared among the sources as the targets are. Rows of equal or null id
    each take their own place. The outcome depends only on the rows and ``seed``. Other columns are ignored; an empty
    table gives no rows.
    """
    spark = docs.sparkSession
    size = F.coalesce(F.regexp_count(F.col(text_col).cast("string"), F.lit(WORD)), F.lit(0)).cast("long")
    base = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).cast("string").alias("source"), size.alias("size"), *([F.struct(*docs.columns).alias("row")] if carry else []))
    base = materialize(base.withColumn("h", F.xxhash64(F.lit(seed), "doc_id", "size")), "sizes")
    totals = base.groupBy("source").agg(F.sum("size").alias("size"), F.count("*").alias("rows")).limit(MOST_SOURCES + 1).collect()
    if len(totals) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    totals.sort(key=lambda r: (r["source"] is None, r["source"] or ""))
    sizes = [r["size"] for r in totals]
    wants = targets(sizes, [weights[i % len(weights)] for i in range(len(totals))], most_repeats, share)
    seats = round(sum(wants) / block)
    shards = max(1, min(-(-seats * block // shard_words), MOST_QUOTAS // max(1, len(totals))))
    ends = np.cumsum(np.array(shard_quotas(wants, seats, shards), np.int64).reshape(shards, len(totals)), axis=0)
    walks = [Walk(r["size"], block, min(int(ends[-1, i]) * block, most_repeats * r["size"]), ends[:, i].copy(), f"{seed}:{r['source']}") for i, r in enumerate(totals)]
    chosen = spark.createDataFrame([(r["source"], i, r["size"], float(want)) for i, (r, want) in enumerate(zip(totals, wants))], "source string, number int, source_size bigint, target double")
    buckets = max(1, -(-sum(r["rows"] for r in totals) // ORDER_ROWS))
    base = base.withColumn("bucket", F.pmod("h", F.lit(buckets)))
    sums = base.groupBy("source", "bucket").agg(F.sum("size").alias("n"))
    earlier = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("before", F.coalesce(F.sum("n").over(earlier), F.lit(0))).drop("n")
    sums = sums.join(chosen.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    sums = sums.withColumnsRenamed({"source": "s", "bucket": "k"})
    within = Window.partitionBy("source", "bucket").orderBy("h", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    placed = base.withColumn("end", F.sum("size").over(within))
    placed = placed.join(sums, F.col("source").eqNullSafe(F.col("s")) & (F.col("bucket") == F.col("k")))
    placed = placed.select("doc_id", "size", "source_size", "target", (F.col("before") + F.col("end") - F.col("size")).alias("start"), "number", *(["row"] if carry else []))
    shared = spark.sparkContext.broadcast(walks)  # MOST_QUOTAS entries at most
    kind = pa.list_(pa.struct([("shard", pa.int32()), ("words", pa.int64())]))

    def select(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            start, size, number = (b.column(c).to_numpy(zero_copy_only=False) for c in ("start", "size", "number"))
            found = []
            for i in np.unique(number):
                at = np.flatnonzero(number == i)
                doc, shard, words = shared.value[i].take(start[at], size[at])
                found.append((at[doc], shard, words))
            doc, shard, words = (np.concatenate([f[k] for f in found] or [np.empty(0, np.int64)]) for k in range(3))
            order = np.argsort(doc, kind="stable")
            bounds = np.searchsorted(doc[order], np.arange(b.num_rows + 1)).astype(np.int32)
            pairs = pa.StructArray.from_arrays([pa.array(shard[order].astype(np.int32)), pa.array(words[order])], fields=list(kind.value_type))
            taken = np.bincount(doc, words, b.num_rows).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("doc_id", "size", "source_size", "target")), pa.array(taken), pa.ListArray.from_arrays(bounds, pairs), *([b.column("row")] if carry else [])], [*TAKEN.split(", "), *(["row"] if carry else [])])

    head = f"doc_id {base.schema['doc_id'].dataType.simpleString()}, size bigint, source_size bigint, target double, taken bigint, shards array<struct<shard:int,words:bigint>>"
    schema = T._parse_datatype_string(head)
    if carry:
        schema = schema.add(base.schema["row"])
    return placed.mapInArrow(select, schema)


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """``docs`` as the mix takes them: each row as many times as the words taken of it, over its size, round to. Rows
    without words are not in the mix; rows of equal or null id are taken each by its own place. All columns are kept,
    whatever their names."""
    taken = mix(docs, carry=True, **options).where("size > 0")
    copies = F.floor(F.col("taken") / F.col("size") + 0.5).cast("int")
    each = taken.select("row", copies.alias("n")).where("n > 0").select("row", F.explode(F.sequence(F.lit(1), F.col("n"))))
    return each.select(*(F.col("row").getField(c).alias(c) for c in docs.columns))
