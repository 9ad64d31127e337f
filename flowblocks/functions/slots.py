"""Timeslot expressions; all are integer arithmetic inside generated code."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

DAY = 86_400


def second_of_day(ts: Column) -> Column:
    return F.hour(ts) * 3600 + F.minute(ts) * 60 + F.second(ts).cast("int")


def uniform(ts: Column, n: int = 48) -> Column:
    """n slots of equal width in a day; 9:00-9:30 is slot 18 of 48."""
    return F.floor(second_of_day(ts) * n / DAY).cast("int")


def custom(ts: Column, bounds: list[int]) -> Column:
    """Slot i holds the seconds of the day in [bounds[i-1], bounds[i])."""
    s = second_of_day(ts)
    return sum(((s >= b).cast("int") for b in sorted(bounds)), F.lit(0)).cast("int")


def equi_depth_bounds(trips: DataFrame, n: int, exact: bool = True) -> list[int]:
    """Quantiles of start times; n - 1 scalars."""
    f = F.percentile if exact else F.percentile_approx
    q = trips.agg(f(second_of_day(F.col("ts")), F.array(*[F.lit(i / n) for i in range(1, n)])).alias("q")).first()[0] or []
    return [int(-(-x // 1)) for x in q]


def classed(ts: Column, base: Column, n: int) -> Column:
    """Weekday slots 0..n-1, weekend slots n+1..2n: the gap keeps a run of slots within one class."""
    return F.when(F.dayofweek(ts).isin(1, 7), base + n + 1).otherwise(base).cast("int")
