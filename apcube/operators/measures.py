"""Cost and accuracy measures."""

from __future__ import annotations

import json
import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F


def are(estimate: DataFrame, truth: DataFrame, keys: Sequence[str], grids: int) -> DataFrame:
    """One row: the mean over ``grids`` bins of |v - A| / max(|v|, |A|); bins absent on a side count 0 there, and a bin of
    two zeros adds nothing."""
    both = estimate.select(*keys, F.col("value").cast("double").alias("v")).join(truth.select(*keys, F.col("value").cast("double").alias("w")), list(keys), "full_outer").fillna(0.0, ["v", "w"])
    term = F.when((F.col("v") == 0) & (F.col("w") == 0), F.lit(0.0)).otherwise(F.abs(F.col("v") - F.col("w")) / F.greatest(F.abs("v"), F.abs("w")))
    return both.agg(F.round(F.coalesce(F.sum(term), F.lit(0.0)) / grids, 6).alias("are"))


def are_of(estimate: Sequence[Row], truth: Sequence[Row], keys: Sequence[str], grids: int) -> float:
    """The same of two charts that have been answered: a row a bin, so their size is that of the grid."""
    v, w = ({tuple(r[k] for k in keys): float(r["value"] or 0) for r in rows} for rows in (estimate, truth))
    pairs = [(v.get(k, 0.0), w.get(k, 0.0)) for k in v.keys() | w.keys()]
    return round(sum(abs(a - b) / max(abs(a), abs(b)) for a, b in pairs if a or b) / grids, 6)


def are_sql(estimate: str, truth: str, keys: Sequence[str], grids: int) -> str:
    using = ", ".join(keys)
    term = "case when v = 0 and w = 0 then 0 else abs(v - w) / greatest(abs(v), abs(w)) end"
    return f"select round(coalesce(sum({term}), 0) / {grids}, 6) as are from (select coalesce(e.value, 0)::double as v, coalesce(t.value, 0)::double as w from ({estimate}) e full join ({truth}) t using ({using}))"


def operations(bins: Sequence[int]) -> dict[str, int]:
    """Additions and subtractions per leaf for a chart of these bins: corner by corner, and by differencing vertices one
    dimension after another."""
    k, cells = len(bins), 1
    for n in bins:
        cells *= n
    batched, done = 0, 1
    for i, n in enumerate(bins):  # differences along axis i of an array whose earlier axes are differenced already
        rest = 1
        for m in bins[i + 1 :]:
            rest *= m + 1
        batched += done * n * rest
        done *= n
    return {"corners": (2**k - 1) * cells, "batched": batched}


def payload(df: DataFrame) -> DataFrame:
    """Bytes of the result as JSON rows."""
    return df.agg(F.coalesce(F.sum(F.octet_length(F.to_json(F.struct(*df.columns)))), F.lit(0)).cast("long").alias("bytes"))


def payload_of(rows: Sequence[Row]) -> int:
    """The same of rows that have been answered."""
    return sum(len(json.dumps(r.asDict(), separators=(",", ":"), default=str).encode()) for r in rows)


def timed(run: Callable[[], object]) -> tuple[float, object]:
    began = time.perf_counter()
    out = run()
    return time.perf_counter() - began, out


def latency(runs: DataFrame, by: str = "config", ms: str = "ms") -> DataFrame:
    """Per config: number of queries, median, mean, deviation, maximum and 90th percentile."""
    return runs.groupBy(by).agg(F.count("*").alias("queries"), F.expr(f"percentile({ms}, 0.5)").alias("median"), F.avg(ms).alias("mean"), F.stddev_samp(ms).alias("deviation"), F.max(ms).alias("maximum"), F.expr(f"percentile({ms}, 0.9)").alias("p90"))


def candidate_quality(found: DataFrame, truth: DataFrame, keys: Sequence[str] = ("query", "box")) -> DataFrame:
    """Recall and precision of candidate pairs."""
    keys = list(keys)
    hit = found.join(truth, keys, "left_semi")
    one = lambda df, n: df.agg(F.count("*").alias(n))
    row = one(found, "found").crossJoin(one(truth, "wanted")).crossJoin(one(hit, "hits"))  # one row each
    return row.select("found", "wanted", "hits", F.round(F.when(F.col("wanted") == 0, 1.0).otherwise(F.col("hits") / F.col("wanted")), 4).alias("recall"), F.round(F.when(F.col("found") == 0, 1.0).otherwise(F.col("hits") / F.col("found")), 4).alias("precision"))
