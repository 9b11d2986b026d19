"""What the operators of this subpackage share: reading tables, cutting lineage, Arrow scans, bounded memos."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gpart.session import checkpointed as cut

__all__ = ["cut", "of", "scan", "table", "utf8", "pieces", "release", "Memo"]

#: ASCII lower-casing, the only case folding of the word contracts.
ASCII_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ASCII_LOWER = "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def of(df: DataFrame, **columns: str) -> DataFrame:
    """Only the named columns, under the operator's own names; whatever else df carries cannot clash."""
    return df.select(*[F.col(f"`{source}`").alias(name) for name, source in columns.items()])


def scan(df: DataFrame, rows: Callable[[pa.RecordBatch], dict[str, list]], schema: str) -> DataFrame:
    """mapInArrow with a function from a batch to columns; the batch's columns are those of df."""
    arrow = _arrow(T._parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch):
                out = rows(part)
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)
        release()

    return df.mapInArrow(run, schema)


def _arrow(schema: T.StructType) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(schema)


def pieces(batch: pa.RecordBatch, most: int = 1024) -> Iterator[pa.RecordBatch]:
    """A batch in slices, so that the Python objects of a few rows are alive at once."""
    for start in range(0, batch.num_rows, most):
        yield batch.slice(start, most)


def utf8(batch: pa.RecordBatch, name: str) -> list[bytes | None]:
    """A string column as bytes, without decoding."""
    return batch.column(name).cast(pa.large_binary()).to_pylist()


def release() -> None:
    """Gives back what a worker has freed, at the end of a task's scan: workers serve many stages one after another, and both the
    Arrow pool and the C library would keep it."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


class Memo(dict):
    """A dict that computes what it lacks and starts afresh when it holds `most` entries; long keys are not kept.

    A Python worker serves many stages one after another: the memo in use is the only one that holds anything.
    """

    active: Memo | None = None

    def __init__(self, make: Callable, most: int = 200_000, longest: int = 64):
        super().__init__()
        self.make, self.most, self.longest = make, most, longest

    def __missing__(self, key):
        value = self.make(key)
        if len(key) <= self.longest:
            if len(self) >= self.most:
                self.clear()
            self[key] = value
        return value

    def use(self) -> Memo:
        if Memo.active is not self:
            if Memo.active is not None:
                Memo.active.clear()
            Memo.active = self
        return self

    def __reduce__(self):
        return Memo, (self.make, self.most, self.longest)
