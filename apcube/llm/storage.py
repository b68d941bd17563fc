"""Intermediate tables in the folder that the driver and all executors share.

``materialize`` cuts lineage by a written Parquet table: a lost executor costs a re-read, never a re-run of
what stands before. The folder is that of ``spark.checkpoint.dir``.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OPEN: dict[str, SparkSession] = {}
_CHOSEN: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder named in ``spark.checkpoint.dir``; where it is unset, one is chosen: a temporary folder in local
    mode (tests), a folder of the warehouse on a cluster."""
    base, app = spark.conf.get("spark.checkpoint.dir", None), spark.sparkContext.applicationId
    if not base:
        if app not in _CHOSEN:
            alone = spark.sparkContext.master.startswith("local") and "cluster" not in spark.sparkContext.master
            _CHOSEN[app] = "file://" + tempfile.mkdtemp(prefix="apcube-") if alone else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_apcube"
        base = _CHOSEN[app]
    return f"{base.rstrip('/')}/apcube-{app}"


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    if not _OPEN:
        atexit.register(_clean)
    _OPEN[path] = spark
    return path


def materialize(df: DataFrame, name: str, codec: str = "zstd", *partition_by: str) -> DataFrame:
    """``df`` written to the shared folder and read back."""
    spark = df.sparkSession
    path = new_path(spark, name)
    # without the empty file that marks success, which nobody reads: a local file system forks the driver's JVM to make it
    writer = df.write.option("compression", codec).option("mapreduce.fileoutputcommitter.marksuccessfuljobs", "false")
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._apcube_path = path
    return out


def hadoop(spark: SparkSession, path: str):
    """(file system, path) of the JVM for a URI."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def publish(spark: SparkSession, path: str, content: bytes) -> bool:
    """Makes ``path`` appear with all of ``content`` at once, unless it exists: False then. Of several writers one gets
    True; one that dies on its way leaves a temporary file and nothing at ``path``.

    The content is written beside it and then linked (local files) or renamed without overwriting (other stores: as
    atomic as the store's own rename; HDFS's is)."""
    temporary = f"{path}.{uuid.uuid4().hex}.tmp"
    system, source = hadoop(spark, temporary)
    stream = system.create(source, False)
    stream.write(bytearray(content))
    stream.close()
    target = hadoop(spark, path)[1]
    try:
        if system.getScheme() == "file":
            place = lambda p: spark._jvm.java.io.File(system.makeQualified(p).toUri().getPath()).toPath()
            spark._jvm.java.nio.file.Files.createLink(place(target), place(source))
        else:
            _rename_new(spark, source, target)
    except Exception as e:
        if "AlreadyExists" in str(e):
            return False
        raise
    finally:
        system.delete(source, False)
    return True


def _rename_new(spark: SparkSession, source, target) -> None:
    kind = getattr(spark._jvm.org.apache.hadoop.fs, "Options$Rename")
    options = spark.sparkContext._gateway.new_array(kind, 1)
    options[0] = kind.NONE
    spark._jvm.org.apache.hadoop.fs.FileContext.getFileContext(target.toUri(), spark._jsc.hadoopConfiguration()).rename(source, target, options)


def drop(*tables: DataFrame | str) -> None:
    """Delete materialized tables that nothing will read again."""
    for t in tables:
        path = t if isinstance(t, str) else getattr(t, "_apcube_path", None)
        if path and path in _OPEN:
            fs, p = hadoop(_OPEN.pop(path), path)
            fs.delete(p, True)


def _clean() -> None:
    for path in list(_OPEN):
        try:
            drop(path)
        except Exception:  # the session has gone: nothing can be deleted through it
            return
