"""Order-preserving codes of column values, so that summaries work on plain int64 arrays (or on text).

Integers, booleans, dates, timestamps and day-time intervals are their own integers; a decimal of up to 18 digits is its unscaled one. A float's bits with
the negative half flipped sort as the floats do; -0.0 folds to 0.0 and every NaN to one that sorts last, as Spark sorts them.
Strings and binaries stay objects; Python compares them as Spark does, byte by byte.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

_LOW = np.int64(0x7FFFFFFFFFFFFFFF)


def float_codes(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64) + 0.0
    x[np.isnan(x)] = np.nan
    bits = x.view(np.int64)
    return bits ^ ((bits >> np.int64(63)) & _LOW)


def code_floats(code: np.ndarray) -> np.ndarray:
    code = np.ascontiguousarray(code, np.int64)
    return (code ^ ((code >> np.int64(63)) & _LOW)).view(np.float64)


class OrderCode:
    """Both ways for one Spark type; `plain` types have integer codes."""

    def __init__(self, kind: T.DataType):
        if isinstance(kind, T.DecimalType) and kind.precision > 18 or isinstance(kind, (T.ArrayType, T.MapType, T.StructType)):
            raise TypeError(f"no order code for {kind.simpleString()}")
        self.kind = kind
        self.plain = not isinstance(kind, (T.StringType, T.BinaryType))

    @property
    def arrow(self) -> pa.DataType:
        return to_arrow_type(self.kind)

    def encode(self, column: pa.Array) -> np.ndarray:
        """Codes of the values that are not null."""
        return self.codes(self.sortable(column))

    def codes(self, values: np.ndarray) -> np.ndarray:
        """Codes of what `sortable` gave, or of some of it."""
        return float_codes(values) if isinstance(self.kind, (T.DoubleType, T.FloatType)) else values

    def sortable(self, column: pa.Array) -> np.ndarray:
        """The values that are not null, as numpy sorts them in the order of their codes: floats as they are, the rest as codes."""
        if isinstance(column, pa.ChunkedArray):
            column = column.combine_chunks()
        if column.null_count:
            column = column.drop_null()
        if isinstance(self.kind, (T.StringType, T.BinaryType)):
            out = np.empty(len(column), object)
            out[:] = column.to_pylist()
            return out
        if isinstance(self.kind, (T.DoubleType, T.FloatType)):
            return column.to_numpy(zero_copy_only=False)
        if isinstance(self.kind, T.DecimalType):
            raw = np.frombuffer(column.buffers()[1], np.int64).reshape(-1, 2) if len(column) else np.zeros((0, 2), np.int64)
            return raw[column.offset : column.offset + len(column), 0].copy()
        if isinstance(self.kind, T.BooleanType):
            column = column.cast(pa.int8())
        if pa.types.is_date32(column.type):
            column = column.cast(pa.int32())
        return column.cast(pa.int64()).to_numpy(zero_copy_only=False)

    def decode(self, codes: np.ndarray) -> pa.Array:
        if not self.plain:
            return pa.array(list(codes), self.arrow)
        codes = np.ascontiguousarray(codes, np.int64)
        if isinstance(self.kind, (T.DoubleType, T.FloatType)):
            return pa.array(code_floats(codes)).cast(self.arrow)
        if isinstance(self.kind, T.DecimalType):
            raw = np.stack([codes, codes >> np.int64(63)], axis=1)
            return pa.Array.from_buffers(self.arrow, len(codes), [None, pa.py_buffer(raw.tobytes())])
        if isinstance(self.kind, T.BooleanType):
            return pc.not_equal(pa.array(codes), 0)
        if pa.types.is_date32(self.arrow):
            return pa.array(codes.astype(np.int32)).cast(self.arrow)
        return pa.array(codes).cast(self.arrow)
