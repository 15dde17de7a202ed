"""What the text operators share."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DataType, MapType, StructType, VariantType


_held: list = [None, None]


def one(key: object, make: Callable[[], object]):  # noqa: ANN201
    """What ``make`` gives, kept for all tasks of a worker process that ask with the same key. A worker keeps one such thing at
    a time: that of a later stage takes the place of an earlier one's, whose memory goes back."""
    if _held[0] is not key and not (isinstance(key, str) and _held[0] == key):
        _held[:] = None, None
        pa.default_memory_pool().release_unused()
        _held[:] = key, make()
    return _held[1]


def binary_column(batch: pa.RecordBatch, name: str) -> Iterator[bytes]:
    """UTF-8 bytes of each row; null counts as empty."""
    column = batch.column(name)
    for value in column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()):
        yield value.as_py() or b""


def text_column(batch: pa.RecordBatch, name: str) -> Iterator[str]:
    for value in batch.column(name):
        yield value.as_py() or ""


def held_out(doc_id: Column) -> Column:
    """Rows that no model may learn from."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def quoted(name: str) -> Column:
    """A column by its name, whatever stands in it."""
    return F.col(f"`{name.replace('`', '``')}`")


def named(docs: DataFrame) -> list[Column]:
    return [quoted(c) for c in docs.columns]


def _hashes(kind: DataType) -> bool:
    """Whether Spark hashes values of a type."""
    if isinstance(kind, ArrayType):
        return _hashes(kind.elementType)
    if isinstance(kind, StructType):
        return all(_hashes(f.dataType) for f in kind.fields)
    return not isinstance(kind, (MapType, VariantType))


def row_hash(docs: DataFrame) -> Column:
    """A number of each row, from all columns that Spark can hash."""
    return F.xxhash64(*[quoted(f.name) for f in docs.schema.fields if _hashes(f.dataType)])
