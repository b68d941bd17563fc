"""Groups of a key, in bounded blocks, from partitions sorted by the key."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def in_blocks(df: DataFrame, key: str, rows: str, member: Column, block: int) -> DataFrame:
    """``df`` with ``unit`` long and ``side`` int, sorted so that the rows of a unit are adjacent in one partition.

    A key's ``rows`` members (a column) are dealt into blocks of about ``block`` by a hash of ``member``; a unit is a
    block with itself (side 0) or a pair of blocks (sides 0 and 1), so that every pair of members meets in one unit
    (pairs within a block in the unit of that block alone) and no unit holds more than about two blocks.
    """
    blocks = F.ceil(F.col(rows) / F.lit(float(block))).cast("int")
    mine = F.pmod(F.xxhash64(F.lit(17), member), blocks).cast("int")
    out = df.withColumn("__blocks", blocks).withColumn("__mine", mine).withColumn("__other", F.explode(F.sequence(F.lit(0), F.col("__blocks") - 1)))
    lo, hi = F.least("__mine", "__other"), F.greatest("__mine", "__other")
    out = out.withColumn("unit", F.xxhash64(key, lo, hi)).withColumn("side", (F.col("__mine") > F.col("__other")).cast("int"))
    return out.drop("__blocks", "__mine", "__other").repartition("unit").sortWithinPartitions("unit")


def runs(batches: Iterator[pa.RecordBatch], key: str = "unit") -> Iterator[pa.RecordBatch]:
    """The runs of equal ``key`` (a long without nulls) of at least two rows, each as one batch."""
    held: list[pa.RecordBatch] = []

    def joined() -> pa.RecordBatch:
        return held[0] if len(held) == 1 else pa.Table.from_batches(held).combine_chunks().to_batches()[0]

    for batch in batches:
        if not batch.num_rows:
            continue
        k = batch.column(key).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(k[1:] != k[:-1]) + 1).tolist(), len(k)]
        for i, (a, b) in enumerate(zip(cuts, cuts[1:])):
            if held and (i or held[0].column(key)[0].as_py() != int(k[a])):
                if sum(x.num_rows for x in held) > 1:
                    yield joined()
                held = []
            held.append(batch.slice(a, b - a))
    if held and sum(x.num_rows for x in held) > 1:
        yield joined()
