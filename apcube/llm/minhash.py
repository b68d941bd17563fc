"""MinHash near-duplicate groups over word shingles.

Universal hash minima -> bands -> buckets -> signature check -> exact check on the full sets -> components by
alternating large-star and small-star.

Shape of the work
-----------------
* Equal shingle sets are folded first, so that exact copies cost one row each from then on.
* A bucket never emits all its pairs. Round one ties every member to the bucket's most central member, the one that
  shares most bucket places with others. Once its components are known, only pairs of a bucket whose members lie in
  *different* components can still change a component. Round two compares the signatures of those in numpy, block by
  block, and emits the pairs near the threshold. The outcome is that of testing every pair of every bucket.
* Only documents that share a bucket have their texts shuffled, for the exact check.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from apcube.llm.components import components
from apcube.llm.groups import in_blocks, runs
from apcube.llm.storage import drop, materialize
from apcube.llm.wordhash import BASE, distinct_per_doc, hash_words, mix, shingle_hashes, slices, text_buffers

MOST_HASHES, MISS = 128, 1e-4
#: Bins of the verification signature, and how many standard deviations below the threshold its estimate must lie for a
#: pair to be rejected without the exact check.
BINS, DEVIATIONS = 1024, 4.5
#: Members of a bucket that are compared at once.
BLOCK = 4096


def banding(threshold: float) -> tuple[int, int]:
    """(bands, rows): the most selective banding of at most 128 minima that misses a pair at the threshold with
    probability 1e-4 at most."""
    for rows in range(16, 0, -1):
        p = min(threshold**rows, 1 - 1e-12)
        bands = math.ceil(math.log(MISS) / math.log(1 - p))
        if bands * rows <= MOST_HASHES:
            return bands, rows
    return MOST_HASHES, 1


def _families(n: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    g = np.random.default_rng(seed)
    a = g.integers(0, 1 << 64, n, np.uint64, endpoint=False) | np.uint64(1)
    return a, g.integers(0, 1 << 64, n, np.uint64, endpoint=False)


def signatures(docs: DataFrame, k: int, bands: int, rows: int, seed: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, n_shingles, fp1, fp2 (fingerprint of the set, null when empty), bands array<long>."""
    a, b = _families(bands * rows, seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text", 2 << 20):
            h, bounds = shingle_hashes(hash_words(*text_buffers(part.column("text"))), k)
            h, bounds = distinct_per_doc(h, bounds)
            n = np.diff(bounds)
            full = np.flatnonzero(n)
            at = bounds[:-1][full]
            band = np.zeros((len(full), bands), np.uint64)
            fp = [np.zeros(len(full), np.uint64)] * 2
            if len(full):
                for i in range(bands * rows):
                    low = np.minimum.reduceat((h * a[i] + b[i]) >> np.uint64(32), at)
                    band[:, i // rows] = mix(band[:, i // rows] * BASE + low + np.uint64(i + 1))
                fp = [np.add.reduceat(mix(h ^ np.uint64(salt)), at) for salt in (0x51ED, 0xA5A5F00D)]
            at_row = np.full(part.num_rows, -1)
            at_row[full] = np.arange(len(full))
            pick = pa.array(np.where(at_row < 0, 0, at_row), mask=at_row < 0)
            lists = pa.ListArray.from_arrays(np.arange(0, band.size + 1, bands).astype(np.int32), pa.array(band.view(np.int64).ravel()))
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), pa.array(n, pa.int64()), *(pa.array(x.view(np.int64)).take(pick) for x in fp), lists.take(pick)],
                ["doc_id", "n_shingles", "fp1", "fp2", "bands"],
            )

    narrow = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    kind = narrow.schema["doc_id"].dataType.simpleString()
    return narrow.mapInArrow(run, f"doc_id {kind}, n_shingles bigint, fp1 bigint, fp2 bigint, bands array<bigint>")


def bin_sketches(h: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """One row of ``BINS`` bytes per document: for each range of hash values a byte of the least hash in it, 0 if it has
    none. ``h`` is ascending within a document."""
    doc = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    cell = doc * BINS + (h >> np.uint64(64 - BINS.bit_length() + 1)).astype(np.int64)
    first = np.ones(len(cell), bool)
    first[1:] = cell[1:] != cell[:-1]
    out = np.zeros((len(bounds) - 1) * BINS, np.uint8)
    out[cell[first]] = (h[first] % np.uint64(255)).astype(np.uint8) + 1
    return out.reshape(-1, BINS)


def _possible(left: np.ndarray, right: np.ndarray, threshold: float) -> np.ndarray:
    """Rows of sketches whose similarity can reach the threshold. The estimate samples the union without replacement:
    m occupied bins of about u = -BINS ln(1 - m / BINS) elements, which sets its deviation."""
    m = ((left | right) != 0).sum(axis=-1)
    agree = ((left == right) & (left != 0)).sum(axis=-1)
    full = np.minimum(m / BINS, 1 - 1e-9)
    unseen = np.maximum(1 + full / np.minimum(np.log1p(-full), -1e-9), 0.01)
    return agree >= m * threshold - DEVIATIONS * np.sqrt(threshold * (1 - threshold) * m * unseen) - 1


def _with_sketches(texts: DataFrame, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text", 2 << 20):
            rows = bin_sketches(*distinct_per_doc(*shingle_hashes(hash_words(*text_buffers(part.column("text"))), k)))
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array([x.tobytes() for x in rows], pa.binary())], [*part.schema.names, "sketch"])

    return texts.mapInArrow(run, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in texts.schema) + ", sketch binary")


def _matrix(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(len(column), -1)


def _agree(pairs: DataFrame, sketches: DataFrame, threshold: float) -> DataFrame:
    """Pairs (a, b) whose signatures leave the threshold possible."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            for at in range(0, x.num_rows, 4096):
                y = x.slice(at, 4096)
                yield y.select(["a", "b"]).filter(pa.array(_possible(_matrix(y.column("sa")), _matrix(y.column("sb")), threshold)))

    both = pairs.join(sketches.select(F.col("rep").alias("a"), F.col("sketch").alias("sa")), "a").join(sketches.select(F.col("rep").alias("b"), F.col("sketch").alias("sb")), "b")
    kind = pairs.schema["a"].dataType.simpleString()
    return both.select("a", "b", "sa", "sb").mapInArrow(run, f"a {kind}, b {kind}")


def _across(member: DataFrame, threshold: float) -> DataFrame:
    """member: key, n (members of the bucket), rep, c (component), bands, sketch -> pairs (a, b) of one bucket and
    different components whose signatures leave the threshold possible, each from the first bucket that it shares."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in runs(batches):
            rep, comp, side, sketch = x.column("rep"), x.column("c").to_numpy(zero_copy_only=False), x.column("side").to_numpy(zero_copy_only=False), _matrix(x.column("sketch"))
            bands = x.column("bands").flatten().to_numpy(zero_copy_only=False).reshape(len(rep), -1)
            key = x.column("key")[0].as_py()
            band = int(np.flatnonzero(bands[0] == key)[0])
            two = bool(side.any())
            most = max(zip(*np.unique(comp, return_counts=True)), key=lambda p: p[1])[0]
            # rows outside the unit's largest component against all rows: every pair across components has one such
            some = np.flatnonzero(comp != most)
            for i in some.tolist():
                other = comp != comp[i]
                other[some[some <= i]] = False
                if two:
                    other &= side != side[i]
                at = np.flatnonzero(other)
                at = at[_possible(sketch[at], sketch[i], threshold)]
                if band and len(at):
                    at = at[~(bands[at, :band] == bands[i, :band]).any(axis=1)]
                if len(at):
                    yield pa.RecordBatch.from_arrays([rep.take(pa.array(np.full(len(at), i))), rep.take(pa.array(at))], ["a", "b"])

    kind = member.schema["rep"].dataType.simpleString()
    units = in_blocks(member, "key", "n", F.col("rep"), BLOCK).select("unit", "side", "key", "rep", "c", "bands", "sketch")
    return units.mapInArrow(run, f"a {kind}, b {kind}").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def _exact(pairs: DataFrame, texts: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """Pairs with den * intersection >= num * union on the full sets of the two texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple = (None, None)
        for batch in batches:
            for x in slices(iter([batch]), "tb", 4 << 20):
                ok = np.zeros(x.num_rows, bool)
                hb, bb = distinct_per_doc(*shingle_hashes(hash_words(*text_buffers(x.column("tb"))), k))
                for i, key in enumerate(x.column("a").to_pylist()):
                    if last[0] != key:
                        one = hash_words(*text_buffers(x.column("ta").slice(i, 1)))
                        last = (key, distinct_per_doc(*shingle_hashes(one, k))[0])
                    left, right = last[1], hb[bb[i] : bb[i + 1]]
                    small, large = sorted((len(left), len(right)))
                    if den * small < num * large:
                        continue
                    at = np.searchsorted(left, right)
                    at[at == len(left)] = 0
                    both = int((left[at] == right).sum()) if len(left) else 0
                    ok[i] = den * both >= num * (len(left) + len(right) - both)
                yield x.select(["a", "b"]).filter(pa.array(ok))

    t = texts.select(F.col("rep").alias("a"), F.col("text").alias("ta"))
    u = texts.select(F.col("rep").alias("b"), F.col("text").alias("tb"))
    kind = pairs.schema["a"].dataType.simpleString()
    return pairs.join(u, "b").join(t, "a").select("a", "b", "ta", "tb").mapInArrow(run, f"a {kind}, b {kind}")


def near_duplicates(docs: DataFrame, k: int = 5, threshold: tuple[int, int] = (4, 5), seed: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of ``docs``: doc_id, n_shingles long, component_id, kept boolean.

    Two documents are linked when den * |A and B| >= num * |A or B| for ``threshold`` = (num, den), A and B their sets
    of distinct ``k``-word shingles; ``component_id`` is the least id reachable. Null and empty texts and texts of white
    space have an empty set and link with nothing; texts of fewer than ``k`` words have their whole sequence as their
    one shingle. Equal texts are one group (its least id stays). Rows of one id and equal texts get equal results; a
    null id is never a representative: such a row has a null component_id and is not kept unless its set links with
    nothing that has an id. Rows of one id and different texts each have their own ``n_shingles``; their links are those of
    one of the texts. Other columns are ignored. An empty table gives no rows.
    """
    num, den = threshold
    bands, rows = banding(num / den)
    sig = materialize(signatures(docs, k, bands, rows, seed, id_col, text_col), "minhash")
    groups = sig.where("n_shingles > 0").groupBy("fp1", "fp2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"))
    groups = materialize(groups, "groups")
    reps = sig.join(groups.select("fp1", "fp2", F.col("rep").alias("doc_id")), ["doc_id", "fp1", "fp2"], "left_semi")
    buckets = reps.select(F.col("doc_id").alias("rep"), F.explode("bands").alias("key"))
    sizes = buckets.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    shared = materialize(buckets.join(sizes, "key").select("key", "rep", "n"), "buckets")
    central = materialize(shared.groupBy("rep").agg(F.sum("n").alias("weight")), "central")
    leaders = shared.join(central, "rep").groupBy("key").agg(F.max(F.struct("weight", "rep")).alias("x")).select("key", F.col("x.rep").alias("leader"))
    source = docs.select(F.col(id_col).alias("rep"), F.col(text_col).cast("string").alias("text")).where(F.col(text_col).isNotNull())
    texts = materialize(_with_sketches(source.join(central.select("rep"), "rep", "left_semi").dropDuplicates(["rep"]), k), "texts")
    sketches = texts.select("rep", "sketch")
    tried = shared.join(leaders, "key").where("rep <> leader").select(F.least("leader", "rep").alias("a"), F.greatest("leader", "rep").alias("b")).distinct()
    tried = materialize(tried, "tried")
    linked = materialize(_exact(_agree(tried, sketches, num / den), texts, k, num, den), "linked")
    forest = materialize(components(linked), "forest")
    member = shared.join(forest.withColumnRenamed("node", "rep"), "rep", "left").select("key", "rep", "n", F.coalesce("component", "rep").alias("c"))
    split = member.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("key")
    member = member.join(split, "key", "left_semi").join(reps.select(F.col("doc_id").alias("rep"), "bands").dropDuplicates(["rep"]), "rep").join(sketches, "rep")
    pairs = _across(materialize(member, "split"), num / den).distinct().join(tried, ["a", "b"], "left_anti")
    later = materialize(_exact(pairs, texts, k, num, den), "later")
    if later.isEmpty():
        final = forest
    else:
        final = materialize(components(forest.select(F.col("node").alias("a"), F.col("component").alias("b")).union(later)), "final")
    drop(shared, central, texts, tried, linked)
    of_set = groups.join(final.withColumnRenamed("node", "rep"), "rep", "left").select("fp1", "fp2", F.coalesce("component", "rep").alias("c"))
    out = sig.select("doc_id", "n_shingles", "fp1", "fp2").join(of_set, ["fp1", "fp2"], "left")
    out = out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("c", "doc_id")).alias("component_id"), F.col("c").alias("group"))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("group").isNull()).alias("kept"))


def deduplicate(docs: DataFrame, k: int = 5, threshold: tuple[int, int] = (4, 5), seed: int = 1) -> DataFrame:
    """``docs`` with one document of each near-duplicate group: that of the least doc_id. Rows without id stay."""
    dropped = near_duplicates(docs, k, threshold, seed).where("not kept and doc_id is not null").select("doc_id").distinct()
    return docs.join(dropped, "doc_id", "left_anti")
