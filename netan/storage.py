"""Tables that cut a plan's lineage.

Everything goes to the folder that all executors share: ``spark.checkpoint.dir`` of the running session. Only where no
such folder is named (a local test session) is one made under the system's temporary folder.

A table of `written` lives until it is dropped, until the `scratch` block around it ends, or until the program does.
"""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}
_WRITTEN: list[tuple[SparkSession, str]] = []
_TABLES: dict[str, str] = {}
_SCRATCH: list[set[str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder for intermediate tables of this session."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        _LOCAL[app] = "file://" + tempfile.mkdtemp(prefix="netan-")
    return _LOCAL[app]


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder, read again: the plan starts anew there and survives lost executors."""
    out = lasting(df, name)
    if _SCRATCH:
        _SCRATCH[-1].add(out._netan_path)
    return out


def lasting(df: DataFrame, name: str) -> DataFrame:
    """`written`, but the table outlives the innermost scratch block; one around that will drop it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/netan/{uuid.uuid4().hex}-{name}"
    _WRITTEN.append((spark, path))
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._netan_path = path
    if len(_SCRATCH) > 1:
        _SCRATCH[-2].add(path)
    return out


def bucketed(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """`written` in so many buckets by the key: a join or group on it with another such table needs no exchange."""
    spark, number = df.sparkSession, uuid.uuid4().hex
    path, table = f"{shared_dir(spark)}/netan/{number}-{name}", f"netan_{number}"
    _WRITTEN.append((spark, path))
    _TABLES[path] = table
    df.write.format("parquet").bucketBy(buckets, key).option("path", path).saveAsTable(table)
    out = spark.table(table)
    out._netan_path = path
    out._netan_buckets = buckets
    if _SCRATCH:
        _SCRATCH[-1].add(path)
    return out


@contextlib.contextmanager
def scratch() -> Iterator[None]:
    """Drops the tables that are `written` in this block, when it is left; a result that needs them is to be `lasting`."""
    _SCRATCH.append(set())
    try:
        yield
    finally:
        mine = _SCRATCH.pop()
        for spark, path in [x for x in _WRITTEN if x[1] in mine]:
            _delete(spark, path)
        _WRITTEN[:] = [x for x in _WRITTEN if x[1] not in mine]


def drop(*tables: DataFrame) -> None:
    """Delete tables that `written` made and nothing reads any more."""
    for df in tables:
        path = getattr(df, "_netan_path", None)
        if path:
            _delete(df.sparkSession, path)
            _WRITTEN[:] = [x for x in _WRITTEN if x[1] != path]


def _delete(spark: SparkSession, path: str) -> None:
    if path in _TABLES:
        spark.sql(f"DROP TABLE IF EXISTS {_TABLES.pop(path)}")
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _clear() -> None:
    for spark, path in _WRITTEN:
        try:
            _delete(spark, path)
        except Exception:  # the session has ended before us
            return
