"""A deterministic, sharded WARC writer and its reader.

Records are dealt to shards by ranges of the page id. The ranges are cut where bytes over id cells reach the shard size:
cells are halved, CELL_BITS times a round, while they hold more, so an id far from the others or a dense run of ids makes
no large shard. The cuts depend on the rows alone (a sampled range partitioner would cut elsewhere in another run). In a
shard records are sorted by id and written as one gzip member each; a file is closed when its compressed size passes the
limit, and a shard has as many files as that takes. Headers and digests are made anew from the payloads.

A writer's files stand in a folder of its own: under temporary names first, then, by a second job, those that the staged
manifest lists under their final names. The commit is a small file that names the folder, published whole and only where
there is none. So a reader sees all of an archive or nothing, of two writers one commits, files of lost attempts are never
listed, and a writer that died anywhere doesn't hinder the next one.
"""

from __future__ import annotations

import base64
import hashlib
import json
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote, unquote

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from apcube.llm.storage import drop, hadoop, materialize, publish

#: Halvings of the cells that hold more than a shard, a round; and those of the first round.
CELL_BITS, FIRST_BITS = 4, 12
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CURRENT = "_current.json"
MANIFEST = "shard int, part int, name string, temp string, records bigint, bytes bigint, sha256 string"


def _files(uri: str):
    """(pyarrow file system, path): executors write through it, whatever store the URI names."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def _name_of(page_id: str | None) -> str:
    return f"<urn:page:{'' if page_id is None else quote(page_id, safe='')}>"


def _id_of(record_id: str) -> str | None:
    return unquote(record_id[len("<urn:page:") : -1]) or None


def _digest(raw: bytes) -> str:
    return base64.b32encode(hashlib.sha1(raw).digest()).decode()


def _record(kind: str, record_id: str, date: str, block: bytes, extra: dict[str, str], content: str) -> bytes:
    head = {"WARC-Type": kind, "WARC-Record-ID": record_id, "WARC-Date": date, **extra, "WARC-Block-Digest": f"sha1:{_digest(block)}", "Content-Type": content, "Content-Length": str(len(block))}
    lines = "".join(f"{k}: {v}\r\n" for k, v in head.items())
    return f"WARC/1.1\r\n{lines}\r\n".encode() + block + b"\r\n\r\n"


def _page(page_id: str | None, url: str | None, payload: bytes, refers_to: str | None, date: str) -> bytes:
    target = quote(url, safe=":/?#[]@!$&'()*+,;=%~") if url else _name_of(page_id)[1:-1]
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    extra = {"WARC-Target-URI": target, "WARC-Payload-Digest": f"sha1:{_digest(payload)}"}
    if refers_to is None:
        return _record("response", _name_of(page_id), date, http + payload, extra, "application/http; msgtype=response")
    extra |= {"WARC-Profile": PROFILE, "WARC-Refers-To": _name_of(refers_to)}
    return _record("revisit", _name_of(page_id), date, http, extra, "application/http; msgtype=response")


def _member(raw: bytes, level: int) -> bytes:
    """One gzip member without a time stamp, so that equal records give equal bytes."""
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(raw) + z.flush()


def cuts_of(rows: DataFrame, key: str, size: str, most: int) -> np.ndarray:
    """Ascending whole numbers that cut the range of ``key`` (long) into runs of at most ``most`` of ``size``, where single
    keys allow it. The driver holds at most 2**CELL_BITS cells per run (and 2**FIRST_BITS more)."""
    ends = rows.agg(F.min(key).alias("lo"), F.max(key).alias("hi")).first()
    if ends["lo"] is None:
        return np.empty(0, np.int64)
    least = -(1 << 63)  # flipping this bit orders longs as unsigned numbers; a cell is their leading bits
    shift, step, heavy, begins, sizes = max(0, ((ends["lo"] - least) ^ (ends["hi"] - least)).bit_length() - FIRST_BITS), 0, None, [], []
    while True:
        cells = rows.where(F.col(key).isNotNull()).select(F.shiftrightunsigned(F.col(key).bitwiseXOR(F.lit(least)), shift).alias("cell"), size)
        if heavy is not None:
            known = rows.sparkSession.createDataFrame(pd.DataFrame({"up": heavy}))
            cells = cells.join(known, F.shiftrightunsigned("cell", step) == F.col("up"), "left_semi")
        found = cells.groupBy("cell").agg(F.sum(size).alias("bytes")).toArrow()
        cell, held = found.column("cell").to_numpy(), found.column("bytes").to_numpy()
        more = (held > most) & (shift > 0)
        begins.append((cell[~more].view(np.uint64) << np.uint64(shift) ^ np.uint64(1 << 63)).view(np.int64))
        sizes.append(held[~more])
        if not more.any():
            break
        heavy, step = cell[more], min(CELL_BITS, shift)
        shift -= step
    begin, held = np.concatenate(begins), np.concatenate(sizes)
    out, run = [], 0
    for i in np.argsort(begin, kind="stable"):
        if run and run + held[i] > most:
            out.append(int(begin[i]))
            run = 0
        run += held[i]
    return np.array(out, np.int64)


def write(pages: DataFrame, out: str, min_payload: int = 0, shard_bytes: int = 64 << 20, file_bytes: int = 8 << 20, date: str = "2000-01-01T00:00:00Z", level: int = 6, id_col: str = "page_id", url_col: str = "url", body_col: str = "html") -> DataFrame:
    """Writes ``pages`` as WARC files in the new folder ``out`` and returns the manifest.

    A null body is an empty payload; a null or empty URL is replaced by a name made of the id. Of records with equal
    payloads of at least ``min_payload`` bytes the one of least id is a response and the others are revisits of it;
    repeated rows of that id are responses all. Rows without id come first, and are never referred to. Other columns
    are ignored. An empty table gives an empty manifest. Equal rows give equal files. A shard holds about ``shard_bytes``
    of payload, a file about ``file_bytes`` compressed; a record larger than either is written whole. Raises
    FileExistsError if ``out`` has been committed, by an earlier writer or by one at the same time.
    """
    spark = pages.sparkSession
    store = out.rstrip("/")
    system, current = hadoop(spark, f"{store}/{CURRENT}")
    if system.exists(current):
        raise FileExistsError(f"{store} has been committed before")
    run_name = f"run-{uuid.uuid4().hex}"
    run_dir = f"{store}/{run_name}"
    system.mkdirs(hadoop(spark, run_dir)[1])
    body = F.coalesce(F.encode(F.col(body_col).cast("string"), "UTF-8"), F.lit(b""))
    base = pages.select(F.col(id_col).cast("bigint").alias("k"), F.col(id_col).cast("string").alias("id"), F.col(url_col).cast("string").alias("url"), body.alias("body"))
    keyed = base.withColumns({"digest": F.unhex(F.sha1("body")), "n": F.octet_length("body").cast("long")})
    digests = materialize(keyed.select("k", "id", "digest", "n"), "digests")
    first = digests.where(F.col("n") >= min_payload).groupBy("digest").agg(F.min("k").alias("first"), F.count("*").alias("c")).where("c > 1 and first is not null").select("digest", "first")
    again = digests.join(first, "digest").where("not (k <=> first)").select("k", "digest", F.col("first").cast("string").alias("refers_to")).distinct()
    cuts = spark.sparkContext.broadcast(cuts_of(digests, "k", "n", shard_bytes))  # a number a shard

    @F.pandas_udf("int")
    def shard_of(k: pd.Series) -> pd.Series:
        least = np.iinfo(np.int64).min
        return pd.Series(np.searchsorted(cuts.value, k.astype("Int64").fillna(least).to_numpy(np.int64), side="right").astype(np.int32))

    shard = shard_of("k")
    none = lambda kind: F.lit(None).cast(kind)
    stream = keyed.select(shard.alias("shard"), "k", F.lit(1).alias("kind"), "digest", none("string").alias("refers_to"), "id", "url", "body")
    stream = stream.union(again.select(shard.alias("shard"), "k", F.lit(0), "digest", "refers_to", none("string"), none("string"), none("binary")))
    stream = stream.repartitionById(len(cuts.value) + 1, F.col("shard")).sortWithinPartitions("shard", "k", "kind", "digest", "url")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, root = _files(run_dir)
        state: dict = {"shard": None, "sink": None}

        def close() -> list:
            if state["sink"] is None:
                return []
            state["sink"].close()
            row = [state["shard"], state["part"], state["name"], state["temp"], state["records"], state["bytes"], state["sum"].hexdigest()]
            state["sink"] = None
            return [pa.record_batch([pa.array([x]) for x in row[:2]] + [pa.array([x]) for x in row[2:]], [x.split()[0] for x in MANIFEST.split(", ")]).cast(_manifest_schema())]

        def put(raw: bytes) -> None:
            member = _member(raw, level)
            state["sink"].write(member)
            state["sum"].update(member)
            state["bytes"] += len(member)
            state["records"] += 1

        key, known = None, {}
        for batch in batches:
            for shard, k, kind, digest, refers_to, page_id, url, body in zip(*(c.to_pylist() for c in batch.columns)):
                if key != (shard, k):
                    key, known = (shard, k), {}
                if not kind:
                    known[digest] = refers_to
                    continue
                if hashlib.sha1(body).digest() != digest:
                    raise ValueError(f"the payload of page {page_id} changed on its way")
                if state["shard"] != shard or state["sink"] is None or state["bytes"] >= file_bytes:
                    yield from close()
                    part = state["part"] + 1 if state["shard"] == shard else 0
                    name = f"part-{shard:06d}-{part:04d}.warc.gz"
                    temp = f"{name}.{uuid.uuid4().hex}.tmp"
                    state.update(shard=shard, part=part, name=name, temp=temp, records=0, bytes=0, sum=hashlib.sha256(), sink=files.open_output_stream(f"{root}/{temp}", compression=None))
                    put(_record("warcinfo", f"<urn:file:{name}>", date, f"format: WARC File Format 1.1\r\nisPartOf: {name}\r\n".encode(), {"WARC-Filename": name}, "application/warc-fields"))
                put(_page(page_id, url, body, known.get(digest), date))
        yield from close()

    staged = materialize(stream.mapInArrow(run, MANIFEST), "staged")

    def move(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, root = _files(run_dir)
        from pyarrow import fs

        for batch in batches:
            for name, temp in zip(batch.column("name").to_pylist(), batch.column("temp").to_pylist()):
                # a retried task finds its file moved already
                if files.get_file_info(f"{root}/{temp}").type != fs.FileType.NotFound:
                    files.move(f"{root}/{temp}", f"{root}/{name}")
                elif files.get_file_info(f"{root}/{name}").type == fs.FileType.NotFound:
                    raise FileNotFoundError(f"{temp} is neither staged nor committed")
            yield batch

    staged.mapInArrow(move, MANIFEST).drop("temp").write.option("compression", "zstd").parquet(f"{run_dir}/_manifest")
    if not publish(spark, f"{store}/{CURRENT}", json.dumps({"run": run_name}).encode()):
        system.delete(hadoop(spark, run_dir)[1], True)
        raise FileExistsError(f"{store} has been committed by another writer")
    drop(digests, staged)
    return manifest(spark, store)


def _committed(spark: SparkSession, store: str) -> str:
    """The committed writer's folder."""
    system, path = hadoop(spark, f"{store}/{CURRENT}")
    stream = system.open(path)
    try:
        return json.loads(bytes(stream.readAllBytes()).decode())["run"]
    finally:
        stream.close()


def manifest(spark: SparkSession, out: str) -> DataFrame:
    """shard, part, name, records, bytes, sha256 and path (from ``out``) of a committed archive's files."""
    run = _committed(spark, out.rstrip("/"))
    return spark.read.parquet(f"{out.rstrip('/')}/{run}/_manifest").withColumn("path", F.concat(F.lit(f"{run}/"), "name"))


def clean(spark: SparkSession, out: str) -> int:
    """Deletes what writers that didn't commit have left, and the lost attempts of the one that did; returns the number of
    folders and files. Other writers must rest."""
    store, gone = out.rstrip("/"), 0
    run = _committed(spark, store)
    for folder, keep in ((store, {run, CURRENT}), (f"{store}/{run}", None)):
        system, path = hadoop(spark, folder)
        for f in system.listStatus(path):
            name = f.getPath().getName()
            if name not in keep if keep is not None else name.endswith(".tmp"):
                system.delete(f.getPath(), True)
                gone += 1
    return gone


def _manifest_schema() -> pa.Schema:
    kinds = {"int": pa.int32(), "string": pa.string(), "bigint": pa.int64()}
    return pa.schema([(x.split()[0], kinds[x.split()[1]]) for x in MANIFEST.split(", ")])


class _Summed:
    """A stream whose bytes are summed up as they are read."""

    def __init__(self, stream):
        self.stream, self.sum = stream, hashlib.sha256()

    def read(self, n: int) -> bytes:
        raw = self.stream.read(n)
        self.sum.update(raw)
        return raw


def members(stream, step: int = 1 << 20) -> Iterator[tuple[int, bytes]]:
    """(offset, content) of each gzip member of a file, one record in memory at a time."""
    at, rest = 0, b""
    while True:
        z, parts, used = zlib.decompressobj(31), [], 0
        while not z.eof:
            chunk = rest or stream.read(step)
            rest = b""
            if not chunk:
                if used:
                    raise ValueError("the file ends within a record")
                return
            parts.append(z.decompress(chunk))
            used += len(chunk)
        rest = z.unused_data
        used -= len(rest)
        yield at, b"".join(parts)
        at += used


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers (names in lower case) and block of one record; its block digest is verified."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    block = rest[: int(fields["content-length"])]
    if len(block) != int(fields["content-length"]) or fields["warc-block-digest"] != f"sha1:{_digest(block)}":
        raise ValueError(f"record {fields['warc-record-id']} is damaged")
    return fields, block


def read(spark: SparkSession, out: str) -> DataFrame:
    """Every page record of a committed archive: page_id string, url, payload_bytes, payload_digest, record_type,
    refers_to string, payload binary (null for revisits), archive, archive_offset. Payload digests and the files' sums in
    the manifest are verified."""
    store = out.rstrip("/")
    names = manifest(spark, store).select("path", "name", "sha256")
    columns = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload", "archive", "archive_offset"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, root = _files(store)
        for path, name, checksum in (x for b in batches for x in zip(*(c.to_pylist() for c in b.columns))):
            rows, size = [], 0
            with files.open_input_stream(f"{root}/{path}", compression=None) as opened:
                stream = _Summed(opened)
                for at, raw in members(stream):
                    fields, block = parse(raw)
                    if fields["warc-type"] == "warcinfo":
                        continue
                    http, _, payload = block.partition(b"\r\n\r\n")
                    length = next(int(x.partition(b":")[2]) for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:"))
                    revisit = fields["warc-type"] == "revisit"
                    digest = fields["warc-payload-digest"].removeprefix("sha1:")
                    if not revisit and (len(payload) != length or _digest(payload) != digest):
                        raise ValueError(f"the payload of {fields['warc-record-id']} is damaged")
                    rows.append((_id_of(fields["warc-record-id"]), fields["warc-target-uri"], length, digest, fields["warc-type"], _id_of(fields["warc-refers-to"]) if revisit else None, None if revisit else payload, name, at))
                    size += len(raw)
                    if size > 8 << 20:
                        yield _rows(rows, columns)
                        rows, size = [], 0
            if stream.sum.hexdigest() != checksum:
                raise ValueError(f"{path} is not the file that was committed")
            if rows:
                yield _rows(rows, columns)

    return names.repartition("name").mapInArrow(run, "page_id string, url string, payload_bytes bigint, payload_digest string, record_type string, refers_to string, payload binary, archive string, archive_offset bigint")


def _rows(rows: list[tuple], columns: list[str]) -> pa.RecordBatch:
    kinds = [pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.binary(), pa.string(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*rows), kinds)], columns)
