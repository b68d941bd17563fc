"""The registered queries of the training-data operators, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from apcube.llm import compaction, imagematch, itq, langid, linededup, minhash, mixing, ngramlm, packing, thumbnails, warc
from apcube.llm.storage import new_path


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op6_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(_read(spark, sf_dir, "documents"), k=3, threshold=(85, 100))


def op1_itq(spark: SparkSession, sf_dir: str) -> DataFrame:
    return itq.near_duplicates(_read(spark, sf_dir, "embeddings"))


def op2_compaction(spark: SparkSession, sf_dir: str) -> DataFrame:
    store = compaction.compacted(_read(spark, sf_dir, "documents"), new_path(spark, "store"))
    return store.read().select("doc_id", "lang", "source", "n_chars", F.octet_length("text").cast("long").alias("n_bytes"), F.md5(F.col("text")).alias("text_md5"))


OP2_SQL = "select doc_id, lang, source, n_chars, strlen(text)::bigint as n_bytes, md5(text) as text_md5 from documents"


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _read(spark, sf_dir, "pages")
    out = new_path(spark, "warc")
    warc.write(pages, out)
    kind = pages.schema["page_id"].dataType
    read = warc.read(spark, out)
    return read.select(F.col("page_id").cast(kind).alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").cast(kind).alias("refers_to"))


#: Each base32 letter of a SHA-1 is five of its 160 bits.
OP3_SQL = """
with p as (select page_id, coalesce(html, '') as html from pages),
d as (select page_id, strlen(html) as payload_bytes, sha1(html) as hex from p),
b as (select *, min(page_id) over (partition by hex) as first, unhex(hex)::bit::varchar as bits from d)
select page_id, payload_bytes::bigint as payload_bytes,
  array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + list_sum(list_transform(range(5), lambda j: (substr(bits, (5 * i + j + 1)::int, 1) = '1')::int * (1 << (4 - j)::int)))::int, 1)), '') as payload_digest,
  case when page_id = first then 'response' else 'revisit' end as record_type,
  case when page_id <> first then first end as refers_to
from b
"""


def op4_image_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every query with every image, whatever their number: the tables alone leave out some pairs."""
    pages = _read(spark, sf_dir, "pages")
    return imagematch.search(thumbnails.thumbnails(pages), thumbnails.edited(thumbnails.thumbnails(pages.where("page_id % 20 = 0"))), exact=True)


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_read(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(_read(spark, sf_dir, "documents"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return packing.pack(_read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op9_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    cleaned = linededup.remove_boilerplate(_read(spark, sf_dir, "documents"))
    return cleaned.select("doc_id", "n_lines", "n_removed", F.md5(F.col("text")).alias("text_md5"))


OP9_SQL = """
with l as (select doc_id, source, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as i from documents),
s as (select trim(line, ' ') as key from l where trim(line, ' ') <> '' group by 1 having count(distinct source) >= 8),
m as (select l.*, s.key is not null as gone from l left join s on trim(l.line, ' ') = s.key),
d as (select doc_id, count(*) as n, count(*) filter (gone) as g, bool_or(not gone and trim(line, ' ') <> '') as page,
  coalesce(string_agg(line, chr(10) order by i) filter (not gone), '') as kept from m group by doc_id)
select doc_id, coalesce(n, 0)::bigint as n_lines, case when g > 0 and page then g else 0 end::bigint as n_removed,
  md5(case when g > 0 and page then kept else text end) as text_md5
from documents left join d using (doc_id)
"""


def op10_interpolated_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = ngramlm.score(_read(spark, sf_dir, "documents"), langid.fold("doc_id", 7) != 2)
    return scored.select("doc_id", (~F.col("counted")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_itq": op1_itq,
        "op2_compaction": op2_compaction,
        "op3_warc": op3_warc,
        "op4_image_copies": op4_image_copies,
        "op5_mixing": op5_mixing,
        "op6_minhash": op6_minhash,
        "op7_language": op7_language,
        "op8_packing": op8_packing,
        "op9_line_spread": op9_line_spread,
        "op10_interpolated_lm": op10_interpolated_lm,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_compaction": OP2_SQL, "op3_warc": OP3_SQL, "op9_line_spread": OP9_SQL}
