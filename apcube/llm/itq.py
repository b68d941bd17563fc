"""Embedding near-duplicates: iterative quantisation, multi-index Hamming tables, rerank by exact cosine.

1. Equal vectors of a label fold into one representative with a count.
2. ``fit`` learns, on a bounded sample, rotations that turn centred vectors into balanced sign codes: alternately the
   nearest binary codes and the orthogonal (Procrustes) rotation towards them. Several rotations from different starts
   give one long code.
3. The code is cut into substrings; each is the key of one Hamming table. Vectors of a label that agree in a whole
   substring meet in a bucket.
4. A bucket's vectors are compared by cosine in double precision in matrix blocks. A pair that meets in several tables
   is counted in the first alone. A block returns counts and a spanning forest, never its pairs, so a group of g near
   copies costs g rows a table; buckets of any size are split into bounded blocks.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from apcube.llm.components import components
from apcube.llm.groups import in_blocks, runs
from apcube.llm.storage import drop, materialize

#: Rows of a block; a unit of work compares at most two blocks.
BLOCK = 2048
#: The centre counts the origin as so many vectors of the sample.
PRIOR = 32


@dataclass
class Codes:
    """Centre and rotations; ``substring`` bits a table. Every rotation gives whole tables."""

    centre: np.ndarray
    rotations: np.ndarray
    substring: int

    @property
    def tables(self) -> int:
        return self.rotations.shape[0] * (self.rotations.shape[2] // self.substring)

    def keys(self, x: np.ndarray) -> np.ndarray:
        """vectors x tables: each substring as a whole number."""
        bits = np.concatenate([((x - self.centre) @ r > 0)[:, : r.shape[1] // self.substring * self.substring] for r in self.rotations], axis=1)
        parts = bits.reshape(len(x), self.tables, self.substring)
        return (parts @ (1 << np.arange(self.substring, dtype=np.int64))).astype(np.int64)


def thinned(sample: np.ndarray, nearest: float = 0.9, block: int = 1024) -> np.ndarray:
    """The unit vectors without those of a cosine of ``nearest`` or more with an earlier one."""
    kept = sample[:0]
    for start in range(0, len(sample), block):
        part = sample[start : start + block]
        part = part[~(part @ kept.T >= nearest).any(axis=1)]
        kept = np.concatenate([kept, part[~np.triu(part @ part.T >= nearest, 1).any(axis=0)]])
    return kept


def fit(sample: np.ndarray, rotations: int = 4, substring: int = 16, rounds: int = 30, seed: int = 5) -> Codes:
    """Iterative quantisation of a sample of unit vectors. Components of little variance are kept: the rotation spreads
    the variance over all bits. A vector of fewer components than ``substring`` has substrings of that many bits.

    Near copies are learned from once, and the centre of few vectors is drawn towards the origin: a centre inside a large
    group would make the signs of its members chance."""
    width, sample = sample.shape[1], thinned(sample)
    centre = sample.sum(axis=0) / (len(sample) + PRIOR)
    x = sample - centre
    _, axes = np.linalg.eigh(x.T @ x + 1e-12 * np.eye(width))
    g = np.random.default_rng(seed)
    out = []
    for _ in range(rotations):
        v = x @ axes
        r = np.linalg.qr(g.normal(size=(width, width)))[0]
        for _ in range(rounds if len(sample) else 0):
            u, _, w = np.linalg.svd(np.where(v @ r > 0, 1.0, -1.0).T @ v)
            r = (u @ w).T
        out.append(axes @ r)
    return Codes(centre, np.array(out), min(substring, width))


def _vectors(column: pa.Array, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, width)


def _forest(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """For each of n nodes the least node that the links (a, b) reach: pointer jumping on whole arrays."""
    least = np.arange(n)
    while True:
        before = least.copy()
        low = np.minimum(least[a], least[b])
        np.minimum.at(least, least[a], low)
        np.minimum.at(least, least[b], low)
        np.minimum.at(least, a, low)
        np.minimum.at(least, b, low)
        least = least[least]
        if (least == before).all():
            return least


def _compare(units: DataFrame, width: int, threshold: float) -> DataFrame:
    """units: unit, side, table, rep, copies, keys, vector -> (a, b, more): vector a is linked with ``more`` rows, and
    belongs with vector b (itself where it is the least of its links)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in runs(batches):
            v = _vectors(x.column("vector"), width)
            v /= np.sqrt((v * v).sum(axis=1))[:, None]
            copies, side = x.column("copies").to_numpy(zero_copy_only=False), x.column("side").to_numpy(zero_copy_only=False)
            keys = x.column("keys").flatten().to_numpy(zero_copy_only=False).reshape(len(v), -1)
            table = x.column("table")[0].as_py()
            if side.any():
                left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
                i, j = np.nonzero(v[left] @ v[right].T >= threshold)
                i, j = left[i], right[j]
            else:
                i, j = np.nonzero(np.triu(v @ v.T >= threshold, 1))
            if table and len(i):
                new = np.ones(len(i), bool)
                for t in range(table):
                    new &= keys[i, t] != keys[j, t]
                i, j = i[new], j[new]
            if len(i):
                more = np.bincount(i, copies[j], len(v)) + np.bincount(j, copies[i], len(v))
                least = _forest(i, j, len(v))
                at = np.flatnonzero(more)
                rep = x.column("rep")
                yield pa.RecordBatch.from_arrays([rep.take(pa.array(at)), rep.take(pa.array(least[at])), pa.array(more[at].astype(np.int64))], ["a", "b", "more"])

    kind = units.schema["rep"].dataType.simpleString()
    return units.mapInArrow(run, f"a {kind}, b {kind}, more bigint")


def near_duplicates(rows: DataFrame, threshold: float = 0.98, sample_rows: int = 20_000, rotations: int = 4, substring: int = 16, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", seed: int = 5) -> DataFrame:
    """Per row: vec_id, n_links long, component_id, kept boolean.

    Linked are rows of one label, not null, whose vectors have a cosine of ``threshold`` or more in double precision and
    meet in a table (exact copies always do). Null, empty and zero vectors and vectors with null or non-finite components
    link with nothing, as do rows without label or id. Vectors of unequal width aren't compared; each width has codes of its own, in jobs of its own.
    ``n_links`` counts the other rows linked directly. The codes are learned on about ``sample_rows`` distinct vectors
    chosen by a hash of the vector; every vector is indexed. Rows of equal id are expected to be equal: each copy then
    counts as a row of its own. Other columns are ignored; an empty table gives no rows.
    """
    base = rows.select(F.col(id_col).alias("vec_id"), F.col(vector_col).cast("array<double>").alias("vector"), F.col(label_col).alias("label"))
    fine = F.col("label").isNotNull() & F.col("vec_id").isNotNull() & F.expr("vector is not null and size(vector) > 0 and forall(vector, x -> x is not null and not isnan(x) and abs(x) <= 1e150) and exists(vector, x -> abs(x) >= 1e-150)")
    usable = base.where(fine)
    widths = usable.groupBy(F.size("vector").alias("w")).count().orderBy("w").collect()  # a row a width
    out = base.where(~F.coalesce(fine, F.lit(False))).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    for w in widths:
        out = out.union(_of_width(usable, w["w"], threshold, sample_rows, rotations, substring, seed))
    return out


def _of_width(usable: DataFrame, width: int, threshold: float, sample_rows: int, rotations: int, substring: int, seed: int) -> DataFrame:
    """vec_id, n_links, component_id, kept of the rows (vec_id, vector, label) whose vectors have ``width`` components."""
    spark = usable.sparkSession
    keyed = usable.where(F.size("vector") == width).select("vec_id", "label", F.transform("vector", lambda x: x + F.lit(0.0)).alias("vector"))
    keyed = keyed.withColumns({"p": F.xxhash64("vector"), "q": F.xxhash64(F.lit(seed), "vector")})  # adding 0.0 made -0.0 equal 0.0
    folds = materialize(keyed.groupBy("label", "p", "q").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies")), "folds")
    reps = materialize(keyed.join(folds.withColumnRenamed("rep", "vec_id"), ["label", "p", "q", "vec_id"]).dropDuplicates(["label", "vec_id"]).select("label", F.col("vec_id").alias("rep"), "copies", "vector", "q"), "vectors")
    share = min(1.0, sample_rows / max(1, reps.count()))
    sample = reps.where(F.pmod("q", F.lit(1 << 20)) < int(share * (1 << 20))).select("rep", "vector").toPandas().sort_values("rep", kind="stable")
    x = np.array(sample["vector"].tolist(), float).reshape(-1, width)
    x /= np.sqrt((x * x).sum(axis=1))[:, None]
    shared = spark.sparkContext.broadcast(fit(x, rotations, substring, seed=seed))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                v = _vectors(b.column("vector"), width)
                keys = shared.value.keys(v / np.sqrt((v * v).sum(axis=1))[:, None])
                lists = pa.ListArray.from_arrays(np.arange(0, keys.size + 1, keys.shape[1]).astype(np.int32), pa.array(keys.ravel()))
                yield pa.RecordBatch.from_arrays([*b.columns, lists], [*b.schema.names, "keys"])

    narrow = reps.select("label", "rep", "copies", "vector")
    head = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in narrow.schema)
    coded = materialize(narrow.mapInArrow(encode, f"{head}, keys array<bigint>"), "codes")
    tables = coded.select("label", "rep", F.posexplode("keys").alias("table", "key"))
    sizes = tables.groupBy("label", "table", "key").agg(F.count("*").alias("n")).where("n > 1")
    members = tables.join(sizes, ["label", "table", "key"]).select(F.xxhash64("label", "table", "key").alias("bucket"), "table", "label", "key", "rep", "n")
    members = members.join(coded.select("label", "rep", "copies", "vector", "keys"), ["label", "rep"])
    units = in_blocks(members, "bucket", "n", F.col("rep"), BLOCK).select("unit", "side", "table", "rep", "copies", "keys", "vector")
    found = materialize(_compare(units, width, threshold), "links")
    more = found.groupBy("a").agg(F.sum("more").alias("more"))
    forest = materialize(components(found.select("a", "b")), "forest")
    of_fold = folds.join(more.withColumnRenamed("a", "rep"), "rep", "left").join(forest.withColumnRenamed("node", "rep"), "rep", "left")
    of_fold = materialize(of_fold.select("label", "p", "q", (F.coalesce("more", F.lit(0)) + F.col("copies") - 1).alias("links"), F.coalesce("component", "rep").alias("c")), "outcome")
    drop(folds, reps, coded, found, forest)
    return keyed.select("vec_id", "label", "p", "q").join(of_fold, ["label", "p", "q"]).select("vec_id", F.col("links").alias("n_links"), F.col("c").alias("component_id"), (F.col("c") == F.col("vec_id")).alias("kept"))
