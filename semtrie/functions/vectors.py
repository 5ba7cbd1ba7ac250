"""Vector arithmetic: SQL expressions for any engine path, Arrow kernels on packed vectors for long ones."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def as_double(v: Column) -> Column:
    return v.cast("array<double>")


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_cosine(a: Column, b: Column) -> Column:
    return F.try_divide(vec_dot(a, b), vec_norm(a) * vec_norm(b))


def vec_l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_scale(a: Column, by) -> Column:
    return F.transform(a, lambda x: x * by)


def vec_mean(v: Column) -> Column:
    """Element-wise mean; partial sums are combined map-side, no list of vectors is collected."""
    return vector_to_array(Summarizer.mean(array_to_vector(as_double(v))))


def vec_quantize(a: Column, levels: int = 127) -> Column:
    """Components as small integers relative to the largest magnitude."""
    top = F.array_max(F.transform(a, lambda x: F.abs(x)))
    return F.transform(a, lambda x: F.round(F.try_divide(x * levels, top)).cast("int"))


SQL_FUNCTIONS = {
    "vec_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
    "vec_norm": ("a ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(a, 0D, (s, x) -> s + x * x))"),
    "vec_cosine": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "try_divide(aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x), sqrt(aggregate(a, 0D, (s, x) -> s + x * x)) * sqrt(aggregate(b, 0D, (s, x) -> s + x * x)))"),
    "vec_l2": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))"),
    "vec_add": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> x + y)"),
    "vec_scale": ("a ARRAY<DOUBLE>, by DOUBLE", "ARRAY<DOUBLE>", "transform(a, x -> x * by)"),
}


def register_sql(spark: SparkSession) -> None:
    """Make the vector functions callable from SQL in this session."""
    for name, (args, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")


def unpack(column) -> np.ndarray:
    """Matrix from a series of packed vectors."""
    if not len(column):
        return np.zeros((0, 0))
    return np.frombuffer(b"".join(bytes(x) for x in column), dtype="<f8").reshape(len(column), -1)


def unit_rows(x: np.ndarray) -> np.ndarray:
    norm = np.sqrt((x * x).sum(1, keepdims=True))
    return x / np.where(norm == 0, 1, norm)


def pack_unit(df: DataFrame, col: str = "emb", out: str = "unit") -> DataFrame:
    """Add the vector scaled to length 1 as packed doubles (a zero vector stays zero)."""

    @F.pandas_udf("binary")
    def packed(v: pd.Series) -> pd.Series:
        if not len(v):
            return pd.Series([], dtype=object)
        return pd.Series([r.tobytes() for r in unit_rows(np.array(v.tolist(), dtype="<f8"))])

    return df.withColumn(out, packed(F.col(col)))


def _dots(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series((unpack(a) * unpack(b)).sum(1)) if len(a) else pd.Series([], dtype="float64")


def dot_packed(a, b) -> Column:
    """Inner product of packed vectors: the cosine, if both are units."""
    return F.pandas_udf(_dots, "double")(a, b)


def quantised_rows(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(scale, length of what rounding left out, one byte per component) of each row."""
    scale = np.abs(x).max(1) / 127
    q = np.round(x / np.where(scale == 0, 1, scale)[:, None]).astype(np.int8)
    return scale, np.sqrt(((x - q * scale[:, None]) ** 2).sum(1)), q


def upper_bounds(sa, ea, qa, sb, eb, qb) -> np.ndarray:
    """A bound on the inner products of unit vectors from their ``quantised_rows``."""
    return (qa.astype(np.float64) * qb).sum(1) * sa * sb + ea + eb + 3 * ea * eb + 1e-9


def _quantised(unit: pd.Series) -> pd.Series:
    if not len(unit):
        return pd.Series([], dtype=object)
    scale, left, q = quantised_rows(unpack(unit))
    head = np.stack([scale, left], axis=1).astype("<f8")
    return pd.Series([h.tobytes() + r.tobytes() for h, r in zip(head, q, strict=True)])


def quantise_packed(unit) -> Column:
    """One byte per component of a packed unit vector, behind its scale and the exact length of what rounding left out."""
    return F.pandas_udf(_quantised, "binary")(unit)


def _upper(a: pd.Series, b: pd.Series) -> pd.Series:
    if not len(a):
        return pd.Series([], dtype="float64")

    def parts(column):
        raw = np.frombuffer(b"".join(bytes(x) for x in column), dtype=np.uint8).reshape(len(column), -1)
        head = np.ascontiguousarray(raw[:, :16]).view("<f8")
        return head[:, 0], head[:, 1], np.ascontiguousarray(raw[:, 16:]).view(np.int8)

    return pd.Series(upper_bounds(*parts(a), *parts(b)))


def upper_bound_packed(a, b) -> Column:
    """A bound the inner product of the two unit vectors cannot exceed, from their quantised forms."""
    return F.pandas_udf(_upper, "double")(a, b)
