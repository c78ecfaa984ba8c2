"""Tables written to the shared folder, and reading helpers.

A lineage is cut only by writing a table to the folder that the cluster names
in ``spark.checkpoint.dir``; every executor can read such a table again after
another one was lost.  A session of one machine (master ``local``) may leave the
setting out, as tests do; on a cluster its absence is an error.

Tables that only feed the next table are removed with :func:`discard` once that
one is written.  Tables that a returned DataFrame still scans stay until
:func:`clean`, which the caller runs when the results were used.
"""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Used only by a session of one machine that names no shared folder.
FALLBACK_DIR = f"{tempfile.gettempdir()}/reuse_engine_shared"
#: Bytes of input (as stored) that one partition of a dealt scan takes, about.
DEAL_BYTES = 64 << 20
#: Rows of a few short columns that may be broadcast; more of them are joined on a salted key.
BROADCAST_ROWS, SALTS = 1_000_000, 32

_written: set[str] = set()
_shared: dict[tuple, tuple[str, StructType]] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return (named or FALLBACK_DIR).rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_dir(spark)}/reuse-{label}-{uuid.uuid4().hex}"
    _written.add(path)
    return path


def materialize(df: DataFrame, label: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` once and return a scan of what was written."""
    spark = df.sparkSession
    path = new_path(spark, label)
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    made = spark.read.schema(df.schema).parquet(path)
    made._reuse_path = path
    return made


def discard(*frames: DataFrame) -> None:
    """Remove tables of :func:`materialize` that no later plan scans."""
    for df in frames:
        path = getattr(df, "_reuse_path", None)
        if path in _written:
            _remove(df.sparkSession, path)


def clean(spark: SparkSession) -> int:
    """Remove every table that this process wrote to the shared folder; their number."""
    paths = list(_written)
    for path in paths:
        _remove(spark, path)
    return len(paths)


def _remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    _written.discard(path)


def stored_bytes(df: DataFrame) -> int:
    """Bytes that the scans of ``df`` read, by the file sizes that the plan knows."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def needs_deal(df: DataFrame) -> bool:
    """True for a scan of fewer files than cores."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return stored_bytes(df) < cores * 2 * DEAL_BYTES and len(df.inputFiles()) < cores


def spread(df: DataFrame) -> DataFrame:
    """Deal a scan of fewer files than cores over all cores.

    The given tables can be one file with one row group, which Spark reads in
    one task; a table with files or bytes enough is left as it is, without a shuffle.
    """
    if not needs_deal(df):
        return df
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(max(cores, -(-stored_bytes(df) // DEAL_BYTES)))


def dealt(df: DataFrame, label: str) -> DataFrame:
    """As :func:`spread`, for rows that are scanned several times: dealt rows are written once."""
    return materialize(spread(df), label) if needs_deal(df) else df


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def few_broadcast(df: DataFrame, limit: int | None = None) -> DataFrame:
    """A broadcast hint where the counted rows prove the bound, else none."""
    return F.broadcast(df) if df.count() <= (BROADCAST_ROWS if limit is None else limit) else df


def join_few(rows: DataFrame, few: DataFrame, key: str, salt: Column, how: str = "inner", limit: int | None = None) -> DataFrame:
    """``rows`` joined with ``few``, a row per key, by broadcast or on (key, salt).

    ``salt`` is a hash of the row: a key that many rows share is dealt over
    ``SALTS`` tasks, each of which has a copy of the key's one row.
    """
    if few.count() <= (BROADCAST_ROWS if limit is None else limit):
        return rows.join(F.broadcast(few), key, how)
    copies = few.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return rows.withColumn("__salt", F.pmod(salt, F.lit(SALTS).cast("long"))).join(copies, [key, "__salt"], how).drop("__salt")


def _exists(spark: SparkSession, path: str) -> bool:
    at = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def _mark(spark: SparkSession, sf_dir: str) -> tuple:
    """Name, time and length of everything directly under a folder."""
    at = spark._jvm.org.apache.hadoop.fs.Path(sf_dir)
    found = at.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(at)
    return tuple(sorted((f.getPath().getName(), f.getModificationTime(), f.getLen()) for f in found))


def shared_table(spark: SparkSession, sf_dir: str, label: str, key: tuple, build: Callable[[], DataFrame]) -> DataFrame:
    """A table that several queries read: written by the first of them, and again when the given tables have changed."""
    full = (spark.sparkContext.applicationId, shared_dir(spark), sf_dir, _mark(spark, sf_dir), label, key)
    if full not in _shared or not _exists(spark, _shared[full][0]):
        made = materialize(build(), label)
        _shared[full] = (made._reuse_path, made.schema)
    path, schema = _shared[full]
    return spark.read.schema(schema).parquet(path)
