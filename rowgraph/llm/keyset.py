"""A set of keys as a bit table of fixed size, broadcast to pre-filter rows before a join.

A row whose key is in the set always passes; others pass if they share a bit.  The join that follows decides.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bits of the table: 16 MB whatever the input.
KEY_BITS = 27
_PAGE_BITS = 20
_SCHEMA = pa.schema([("page", pa.int32()), ("bits", pa.binary())])


def _slot(key: Column) -> Column:
    return F.shiftrightunsigned(F.xxhash64(key), 64 - KEY_BITS)


def _pages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def done() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([current], pa.int32()), pa.array([zstandard.compress(np.packbits(bits).tobytes(), 1)], pa.binary())], schema=_SCHEMA)

    current, bits = None, np.zeros(1 << _PAGE_BITS, bool)
    for batch in batches:
        slots = batch.column(0).to_numpy()
        pages = slots >> _PAGE_BITS
        for page in np.unique(pages).tolist():
            if page != current:
                if current is not None:
                    yield done()
                current, bits = page, np.zeros(1 << _PAGE_BITS, bool)
            bits[slots[pages == page] & ((1 << _PAGE_BITS) - 1)] = True
    if current is not None:
        yield done()


def key_table(keys: DataFrame, unique: bool = False) -> bytearray:
    """The table of all values of the only column of ``keys``; ``unique``: no value occurs twice, so none has to be dropped."""
    slots = keys.select(_slot(F.col(keys.columns[0])).alias("slot"))
    slots = slots if unique else slots.distinct()
    slots = slots.repartition(F.shiftright("slot", _PAGE_BITS)).sortWithinPartitions("slot")
    table, size = bytearray(1 << (KEY_BITS - 3)), 1 << (_PAGE_BITS - 3)
    for page, bits in slots.mapInArrow(_pages, "page int, bits binary").collect():
        table[page * size : (page + 1) * size] = zstandard.decompress(bits)
    return table


def in_table(table: bytearray, rows: DataFrame, key: Column, out: str) -> DataFrame:
    """``rows`` with a boolean column: whether the key may be in the set.  Only slots go through Python."""
    given = rows.sparkSession.sparkContext.broadcast(zstandard.compress(bytes(table), 1))

    @F.pandas_udf("boolean")
    def known(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        bits = np.frombuffer(zstandard.decompress(given.value), np.uint8)
        for slot in batches:
            s = slot.to_numpy()
            yield pd.Series((bits[s >> 3] >> (7 - (s & 7)).astype(np.uint8)) & 1 > 0)

    return rows.withColumn(out, known(_slot(key)))


def without_keys(rows: DataFrame, gone: DataFrame, key: str) -> DataFrame:
    """The rows, with all their columns, whose ``key`` isn't among the values of the only column of ``gone``.

    Most rows are passed by the table where they lie; only those that may be gone are shuffled for the join that decides.
    """
    columns = rows.columns
    plain = rows.select(*(F.col(f"`{c}`").alias(f"in_{i}_") for i, c in enumerate(columns)))
    own = f"in_{columns.index(key)}_"
    marked = in_table(key_table(gone), plain, F.col(own), "has_")
    sure = marked.filter("not has_")
    maybe = marked.filter("has_").join(gone.select(F.col(gone.columns[0]).alias(own)), own, "left_anti").select(*marked.columns)
    return sure.unionByName(maybe).select(*(F.col(f"in_{i}_").alias(c) for i, c in enumerate(columns)))
