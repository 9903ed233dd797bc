"""What the operators share: ids and texts of a table, and Arrow helpers for the Python stages."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def keyed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *more: Column) -> DataFrame:
    """(doc_id, text, more...): other columns of the input, clashing names included, go no further."""
    return docs.select(docs[id_col].alias("doc_id"), docs[text_col].cast("string").alias("text"), *more)


def row_key(docs: DataFrame) -> DataFrame:
    """keyed() rows with rid, a hash of id and text: (doc_id, rid) tells rows apart even where ids repeat or are null."""
    return docs.withColumn("rid", F.xxhash64("doc_id", "text"))


def same_row(a: DataFrame, b: DataFrame) -> Column:
    return (a["rid"] == b["rid"]) & a["doc_id"].eqNullSafe(b["doc_id"])


def give_back() -> None:
    """Return freed memory to the system: a worker that waits for its next task, or for another operator's, holds little."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim is not None:
        trim(0)


_KEPT: dict = {}


def kept(key, make: Callable):
    """What make() gives, kept by this Python worker under the key from task to task; one thing is kept at a time."""
    if key not in _KEPT:
        _KEPT.clear()
        _KEPT[key] = make()
    return _KEPT[key]


def forget() -> None:
    _KEPT.clear()


def arrow_map(df: DataFrame, work: Callable[[Iterator[pa.RecordBatch]], Iterator[dict]], schema: T.StructType, keeps: bool = False) -> DataFrame:
    """mapInArrow for a function that yields dicts of columns (lists or arrays); without keeps, workers drop what is `kept`."""
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not keeps:
            forget()
        for columns in work(batches):
            yield pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) for f in arrow], schema=arrow)
        columns = None
        give_back()

    return df.mapInArrow(run, schema)


#: Bytes after which a batch for a Python worker is sent; a vector grows by doubling, so that just less than a power of 2 fits in it.
BATCH_BYTES = 7 << 20


@contextlib.contextmanager
def light_batches(spark: SparkSession) -> Iterator[None]:
    """Batches for Python workers close at BATCH_BYTES in jobs that run within: else one holds 10,000 texts, in the JVM and in the worker."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(BATCH_BYTES))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def fields(df: DataFrame, *names: str) -> list[T.StructField]:
    """Fields of df by name, nullable."""
    return [T.StructField(n, df.schema[n].dataType, True) for n in names]


class Numbers(dict):
    """Numbers of strings in the order of their first lookup; those that the caller has not dealt with yet are in `fresh`."""

    def __init__(self) -> None:
        super().__init__()
        self.fresh: list[str] = []

    def __missing__(self, piece: str) -> int:
        k = self[piece] = len(self)
        self.fresh.append(piece)
        return k


def by_bytes(texts: list, most: int = 1 << 22) -> Iterator[tuple[int, int]]:
    """Ranges [a, b) of texts that hold about `most` characters each; a longer text makes a range of its own."""
    return by_sizes((len(x) if x is not None else 0 for x in texts), most)


def by_sizes(sizes: Iterable[int], most: int) -> Iterator[tuple[int, int]]:
    """Ranges [a, b) whose sizes sum to about `most`; a larger one makes a range of its own."""
    a, end, size = 0, 0, 0
    for n in sizes:
        if size + n > most and end > a:
            yield a, end
            a, size = end, 0
        size += n
        end += 1
    if a < end:
        yield a, end
