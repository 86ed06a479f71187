"""Vector arithmetic, validity, fixed point and a portable hash as Column expressions (no Python on executors)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FIXED = 10_000


def dot(a: Column, b: Column, kind: str = "double") -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast(kind) * y.cast(kind)), F.lit(0).cast(kind), lambda s, x: s + x)


def norm2(a: Column, kind: str = "double") -> Column:
    return dot(a, a, kind)


def l2sq(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def scale(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x * by)


def unit(a: Column) -> Column:
    """Unit length; a zero vector stays zero."""
    n = F.sqrt(norm2(a))
    return F.when(n > 0, F.transform(a, lambda x: x.cast("double") / n)).otherwise(F.transform(a, lambda x: x.cast("double")))


def root_normalize(a: Column) -> Column:
    """Signed square root after L1 normalisation."""
    n = F.aggregate(a, F.lit(0.0), lambda s, x: s + F.abs(x.cast("double")))
    return F.when(n > 0, F.transform(a, lambda x: F.signum(x.cast("double")) * F.sqrt(F.abs(x.cast("double")) / n))).otherwise(F.transform(a, lambda x: F.lit(0.0)))


def to_fixed(a: Column) -> Column:
    """Fixed point: exact sums in any order."""
    return F.transform(a, lambda x: F.floor(x.cast("double") * FIXED + 0.5).cast("long"))


def portable_hash(id_col: Column, salt: str | int) -> Column:
    """28 bits of md5, equal in every SQL engine."""
    return F.conv(F.substring(F.md5(F.concat(id_col.cast("string"), F.lit(f":{salt}"))), 1, 7), 16, 10).cast("long")


def valid(vec: Column, d: int | None = None) -> Column:
    ok = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < F.lit(float("inf"))))
    ok = vec.isNotNull() & F.coalesce(ok, F.lit(False))
    return ok if d is None else ok & (F.size(vec) == d)


def dimension(df: DataFrame, vec_col: str = "vec") -> int:
    low, high = df.where(valid(F.col(vec_col))).agg(F.min(F.size(vec_col)), F.max(F.size(vec_col))).first()
    if low != high:
        raise ValueError(f"vectors of {low} to {high} components")
    return low or 0


def validate(df: DataFrame, invalid: str = "error", vec_col: str = "vec") -> DataFrame:
    """Rows with usable vectors of one length. invalid: error | skip | quarantine (adds a flag, drops nothing)."""
    ok = valid(F.col(vec_col), dimension(df, vec_col))
    if invalid == "skip":
        return df.where(ok)
    if invalid == "quarantine":
        return df.withColumn("usable", ok)
    if invalid != "error":
        raise ValueError(f"unknown policy {invalid!r}")
    if not df.where(~ok).isEmpty():
        raise ValueError("null, non-finite or odd-sized vectors; use invalid='skip' or 'quarantine'")
    return df
