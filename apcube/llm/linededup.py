"""Removal of lines that many sites share, from HyperLogLog sketches of the sites of each line.

1. Lines are hashed (two longs) and written once, without their texts, with their document and place.
2. A line on ``min_sites`` sites has at least as many occurrences, so a plain count comes first and leaves few lines.
3. For those, one sketch of the sites per line hash; sketches merge by aggregation, so that a line on a third of all
   pages is combined before the shuffle.
4. Lines whose estimate lies within five standard errors of the threshold, or within two sites, are counted exactly.
5. Documents get the places of their removed lines and keep the others, in time linear in their length.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from apcube.llm.storage import materialize

#: Registers of a sketch (log2), and its relative standard error.
LG_K = 12
ERROR = 1.04 / 2 ** (LG_K / 2)


KEY = ["k1", "k2"]


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _document(docs: DataFrame, id_col: str, text: Column) -> list[Column]:
    """What tells documents apart: the id (which may be null) and a hash of the text, as rows of one id may differ."""
    return [F.col(id_col).alias("doc_id"), F.xxhash64(F.lit(31), text).alias("doc_hash")]


def spread_lines(docs: DataFrame, min_sites: int, id_col: str, text_col: str, site: Column) -> tuple[DataFrame, DataFrame]:
    """(lines: doc_id, doc_hash, place, k1, k2, site, of lines that aren't blank; shared: k1, k2 of every line on at least
    ``min_sites`` distinct sites)."""
    text = F.col(text_col).cast("string")
    rows = docs.select(*_document(docs, id_col, text), site.cast("string").alias("site"), _lines(text).alias("lines"))
    rows = rows.select("doc_id", "doc_hash", "site", F.posexplode("lines").alias("place", "line"))
    key = F.trim("line")
    hashed = rows.where(key != "").select("doc_id", "doc_hash", "place", F.xxhash64(key).alias("k1"), F.xxhash64(F.lit(29), key).alias("k2"), "site")
    lines = materialize(hashed, "lines")
    often = materialize(lines.groupBy(*KEY).agg(F.count("site").alias("n")).where(F.col("n") >= min_sites).select(*KEY), "often")
    sketches = lines.select(*KEY, "site").join(often, KEY, "left_semi").groupBy(*KEY).agg(F.hll_sketch_agg("site", F.lit(LG_K)).alias("sketch"))
    estimates = materialize(sketches.select(*KEY, F.hll_sketch_estimate("sketch").alias("sites")), "estimates")
    margin = max(2.0, 5 * ERROR * min_sites)
    sure = estimates.where(F.col("sites") > min_sites + margin).select(*KEY)
    near = estimates.where(F.abs(F.col("sites") - min_sites) <= margin).select(*KEY)
    exact = lines.select(*KEY, "site").join(near, KEY, "left_semi").where("site is not null").distinct().groupBy(*KEY).agg(F.count("*").alias("sites"))
    shared = sure.union(exact.where(F.col("sites") >= min_sites).select(*KEY))
    return lines, materialize(shared, "shared")


def remove_boilerplate(docs: DataFrame, min_sites: int = 8, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source") -> DataFrame:
    """``docs`` with the cleaned text in ``text_col`` and two more columns, n_lines and n_removed (long).

    A line counts as boilerplate when it stands, outer blanks apart, on at least ``min_sites`` distinct sites; every
    occurrence goes, whatever its share of the document. Only a document in which every line that isn't blank is
    boilerplate is a copy rather than a page with boilerplate: it stays as it is, for document de-duplication. Blank
    lines stay. Null texts stay null (0 lines), an empty text has one blank line. A null site is no site: its lines count
    for none but can be removed. Rows with null or equal ids are cleaned like others, each by its own text. A text of any
    length is handled whole. Column names are free, but for n_lines and n_removed, which are replaced.
    """
    lines, shared = spread_lines(docs, min_sites, id_col, text_col, F.col(site_col))
    gone = lines.join(shared, KEY, "left_semi").select("doc_id", "doc_hash", "place").distinct()
    per_doc = gone.groupBy(F.col("doc_id").alias("d"), F.col("doc_hash").alias("h")).agg(F.collect_list("place").alias("gone"))
    rest = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    text = F.col(text_col).cast("string")
    # The caller's other columns travel in one struct, so that no name can clash; the lines in place of the text. The split
    # stands before the join lest the optimizer move it into the loop over the lines.
    others = [c for c in rest if c != text_col]
    base = docs.select(F.struct(F.lit(0), *others).alias("row"), *_document(docs, id_col, text), _lines(text).alias("line"))
    base = base.join(per_doc, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("doc_hash") == F.col("h")), "left")
    # array_except works by hashing: a long document with many removed lines costs no more than its length
    left = F.array_except(F.sequence(F.lit(0), F.size("line") - 1), F.col("gone"))
    base = base.withColumn("kept", F.when(F.col("gone").isNotNull(), F.transform(left, lambda i: F.get("line", i))))
    base = base.withColumn("kept", F.when(F.exists("kept", lambda x: F.trim(x) != ""), F.col("kept")))
    n = F.when(F.col("line").isNull(), 0).otherwise(F.size("line")).cast("long")
    return base.select(
        *(F.array_join(F.coalesce("kept", "line"), "\n").alias(c) if c == text_col else F.col("row").getField(c).alias(c) for c in rest),
        n.alias("n_lines"),
        F.when(F.col("kept").isNull(), 0).otherwise(n - F.size("kept")).cast("long").alias("n_removed"),
    )
