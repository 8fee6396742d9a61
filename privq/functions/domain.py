"""Public domains: bounds, clamping, missing values, separation and the affine map to unit gaps.

Bounds are constants that the caller knows without looking at the data. Values outside are clamped, never dropped, so
that a row stays a row. Null and NaN become a bound, or are dropped where the number of rows need not be fixed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privq.functions import prf


@dataclass(frozen=True)
class Domain:
    """[lo, hi] with separation ``gap``; ``psi`` is the ratio that bounds the error."""

    lo: float
    hi: float
    gap: float = 1.0

    def __post_init__(self) -> None:
        if not self.hi > self.lo or not self.gap > 0:
            raise ValueError("a domain needs lo < hi and a positive gap")

    @property
    def psi(self) -> float:
        return (self.hi - self.lo) / self.gap

    def with_gap(self, gap: float) -> Domain:
        return Domain(self.lo, self.hi, gap)


def as_double(df: DataFrame, name: str) -> Column:
    """A number, day or microsecond as a double; booleans, strings and nested types are refused."""
    kind = df.schema[name].dataType
    column = F.col(name)
    if isinstance(kind, T.DateType):
        return F.unix_date(column).cast("double")
    if isinstance(kind, T.TimestampType | T.TimestampNTZType):
        return F.unix_micros(column.cast("timestamp")).cast("double")
    if isinstance(kind, T.DayTimeIntervalType):
        return column.cast("bigint").cast("double")
    if not isinstance(kind, T.NumericType):
        raise TypeError(f"{name} is {kind.simpleString()}; a numeric, date or time column is needed")
    return column.cast("double")


def clamp(x: Column, domain: Domain) -> Column:
    return F.greatest(F.lit(float(domain.lo)), F.least(F.lit(float(domain.hi)), x))


def to_domain(df: DataFrame, name: str, domain: Domain, on_null: str = "drop", keep: tuple[str, ...] = ()) -> DataFrame:
    """``keep`` and ``value double`` inside the domain. on_null: drop, lo or hi."""
    x = as_double(df, name)
    x = F.when(F.isnan(x), None).otherwise(x)
    if on_null == "drop":
        df = df.where(x.isNotNull())
    elif on_null in ("lo", "hi"):
        x = F.coalesce(x, F.lit(float(getattr(domain, on_null))))
    else:
        raise ValueError("on_null must be drop, lo or hi")
    return df.select(*keep, clamp(x, domain).alias("value"))


def to_unit(x: Column, domain: Domain) -> Column:
    return (x - domain.lo) / domain.gap


def from_unit(x: Column, domain: Domain) -> Column:
    return x * domain.gap + domain.lo


def separate(df: DataFrame, how: str, key: str, amount: float, row_key: list[str], value: str = "value") -> DataFrame:
    """Break ties. ``row_key``: uniform jitter in [0, amount) by the row's key; ``gaussian``: of deviation ``amount``.

    Both look at one row only, so neighbouring inputs stay neighbours. Spreading by sorted position is no part of this:
    it moves all later points when one is added, and is only applied to extracted slices (``spread_slices``).
    """
    tagged = F.concat_ws("|", *[F.col(c).cast("string") for c in row_key])
    place = F.conv(F.substring(F.md5(tagged), 1, 13), 16, 10).cast("bigint")
    if how == "row_key":
        noise = amount * prf.uniform(key, "jitter", place)
    elif how == "gaussian":
        noise = prf.gaussian(key, amount, "jitter", place)
    else:
        raise ValueError("how must be row_key or gaussian")
    return df.withColumn(value, F.col(value) + noise)


def spread_slices(slices: DataFrame, gap: float) -> DataFrame:
    """Add ``gap * rank`` to order statistics (``rank``, ``x``): the sorted-position spread, which is not private."""
    return slices.withColumn("x", F.col("x") + gap * F.col("rank"))
