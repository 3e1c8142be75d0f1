"""Words: fixed-width values as raw bits, and bits back as values.  Only bits move, so every payload survives."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf

#: word type -> (width in bytes, numpy type of the bits, numpy type of the values)
TYPES = {"f64": (8, np.int64, np.float64), "f32": (4, np.int32, np.float32), "f16": (2, np.int16, np.float16), "i64": (8, np.int64, np.int64), "i32": (4, np.int32, np.int32)}


def _bits64(v: pa.Array) -> pa.Array:
    return pa.Array.from_buffers(pa.int64(), len(v), v.buffers(), v.null_count, v.offset)


def _bits32(v: pa.Array) -> pa.Array:
    return pa.Array.from_buffers(pa.int32(), len(v), v.buffers(), v.null_count, v.offset).cast(pa.int64())


def _bits16(v: pa.Array) -> pa.Array:
    x = v.fill_null(0.0).to_numpy(zero_copy_only=False).astype(np.float16).view(np.int16).astype(np.int64)
    return pa.array(x, mask=v.is_null().to_numpy(zero_copy_only=False))


def _value64(v: pa.Array) -> pa.Array:
    return pa.Array.from_buffers(pa.float64(), len(v), v.buffers(), v.null_count, v.offset)


def _value32(v: pa.Array) -> pa.Array:
    x = v.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int32).view(np.float32)
    return pa.array(x, mask=v.is_null().to_numpy(zero_copy_only=False))


def word_bits(c: Column, word: str) -> Column:
    """The raw bits of a value as a long (sign-extended for narrow words)."""
    if word == "f64":
        return arrow_udf(_bits64, "bigint")(c.cast("double"))
    if word == "f32":
        return arrow_udf(_bits32, "bigint")(c.cast("float"))
    if word == "f16":
        return arrow_udf(_bits16, "bigint")(c.cast("float"))
    return c.cast("long")


def bits_word(c: Column, word: str) -> Column:
    """The value behind raw bits; half floats come as floats."""
    if word == "f64":
        return arrow_udf(_value64, "double")(c)
    if word == "f32":
        return arrow_udf(_value32, "float")(c)
    return c


def ieee_fields(bits: Column, word: str) -> dict[str, Column]:
    """Sign, biased exponent and mantissa by shifts and masks."""
    e, m = {"f64": (11, 52), "f32": (8, 23), "f16": (5, 10)}[word]
    return {
        "sign": F.shiftrightunsigned(bits, e + m).bitwiseAND(F.lit(1)).cast("int"),
        "exponent": F.shiftrightunsigned(bits, m).bitwiseAND(F.lit((1 << e) - 1)).cast("int"),
        "mantissa": bits.bitwiseAND(F.lit((1 << m) - 1)).cast("long"),
    }


def ieee_value(sign: Column, exponent: Column, mantissa: Column, word: str) -> Column:
    """(-1)^s 2^(e - bias) (1 + m / 2^bits), and the subnormal form for exponent 0."""
    e, m = {"f64": (11, 52), "f32": (8, 23), "f16": (5, 10)}[word]
    bias = (1 << (e - 1)) - 1
    unit = mantissa / F.lit(float(1 << m))
    size = F.when(exponent == 0, F.pow(F.lit(2.0), F.lit(1.0 - bias)) * unit).otherwise(F.pow(F.lit(2.0), exponent - F.lit(bias)) * (1 + unit))
    return F.when(sign == 1, -size).otherwise(size)


def shifted(bits: Column, by: Column) -> Column:
    """Unsigned right shift by a column."""
    return F.call_function("shiftrightunsigned", bits, by.cast("int"))


def plane(bits: Column, width: int, p: int) -> Column:
    """Byte ``p`` of a word, 0 the most significant."""
    return F.shiftrightunsigned(bits, 8 * (width - 1 - p)).bitwiseAND(F.lit(255)).cast("int")


def as_planes(data: bytes, width: int) -> np.ndarray:
    """(words, width) byte matrix of little-endian words, most significant byte first."""
    return np.frombuffer(data, np.uint8).reshape(-1, width)[:, ::-1]


def from_planes(m: np.ndarray) -> bytes:
    return np.ascontiguousarray(m[:, ::-1]).tobytes()
