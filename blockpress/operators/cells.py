"""Cells of coded rows in numpy: lists of codes, or, in tables of zeros and ones, bits packed to bytes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Cells that are unpacked at once.
SLICE_CELLS = 1 << 21


def is_packed(column: pa.Array | pa.ChunkedArray) -> bool:
    return pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type)


def packed_bytes(column: pa.Array) -> np.ndarray:
    """Rows of bytes of one length as a matrix."""
    _, ends, data = column.buffers()
    ends = np.frombuffer(ends, np.int64 if pa.types.is_large_binary(column.type) else np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data or b"", np.uint8)[ends[0] : ends[-1]].reshape(len(column), -1)


def bit_slices(column: pa.Array, n: int) -> Iterator[np.ndarray]:
    """Stretches of packed rows as matrices of 0 and 1, ``SLICE_CELLS`` (or a row) at most."""
    rows, step = packed_bytes(column), max(1, SLICE_CELLS // n)
    for lo in range(0, len(rows), step):
        yield np.unpackbits(rows[lo : lo + step], axis=1, count=n)


def cells_of(column: pa.Array | pa.ChunkedArray, n: int) -> np.ndarray:
    """All rows of a column of codes as a matrix."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if is_packed(column):
        return np.unpackbits(packed_bytes(column), axis=1, count=n)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, n)


def holds_bits(codes: DataFrame) -> bool:
    return isinstance(codes.schema["codes"].dataType, T.BinaryType)


def unpacked(codes: DataFrame, n: int) -> DataFrame:
    """``codes`` with the cells as lists, where they are packed."""
    if not holds_bits(codes):
        return codes
    place = codes.columns.index("codes")
    schema = T.StructType([T.StructField("codes", T.ArrayType(T.ShortType())) if f.name == "codes" else f for f in codes.schema])
    step = max(1, SLICE_CELLS // n)

    def emit(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, step):
                part = batch.slice(lo, step)
                cells = cells_of(part.column(place), n).astype(np.int16)
                at = np.arange(len(cells) + 1, dtype=np.int32) * n
                columns = list(part.columns)
                columns[place] = pa.ListArray.from_arrays(pa.array(at), pa.array(cells.ravel()))
                yield pa.record_batch(columns, names=part.schema.names)

    return codes.mapInArrow(emit, schema)
