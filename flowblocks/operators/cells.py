"""Cells: the one pass over the trips. Hot cells: the share s_a of cells with the largest flow."""
from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EXACT_BITS = 11


def aggregate(trips: DataFrame, endpoints: str = "start") -> DataFrame:
    """o, d, t, flow; with endpoints='start_end' cells are (o, d, t, t_end), t_end the slot of the trip's end."""
    if endpoints not in ("start", "start_end"):
        raise ValueError(endpoints)
    key = ["o", "d", "t"] + ["t_end"] * (endpoints == "start_end")
    return trips.groupBy(*key).agg(F.sum("pax").alias("flow")).where("flow > 0")


def _place(x: Column) -> tuple[Column, Column]:
    """(how many low bits are cut, what remains): at most 2^EXACT_BITS places for each bit length."""
    cut = F.greatest(F.length(F.bin(x)) - EXACT_BITS, F.lit(0))
    return cut, F.call_function("shiftright", x, cut)


def minsup(cells: DataFrame, s_a, rounding: str = "floor") -> tuple[int, int]:
    """(flow at rank s_a * n, n). A histogram of flows to EXACT_BITS significant bits (of bounded size, whatever the cells)
    finds the place of the rank; only flows of more bits need the same again inside that place."""
    s_a = Fraction(str(s_a))
    if not 0 < s_a <= 1:
        raise ValueError("s_a must be in (0, 1]")
    base, left, n, rank = 0, cells.select("flow"), None, 0
    while True:
        cut, rest = _place(F.col("flow") - base)
        bins = sorted(((r.cut, r.rest, r.k) for r in left.groupBy(cut.alias("cut"), rest.alias("rest")).agg(F.count("*").alias("k")).collect()), key=lambda b: b[1] << b[0], reverse=True)
        if n is None:
            n = sum(k for *_, k in bins)
            if not n:
                return 0, 0
            rank = max(1, s_a.numerator * n // s_a.denominator if rounding == "floor" else -(-s_a.numerator * n // s_a.denominator))
        for c, r, k in bins:
            if k >= rank:
                break
            rank -= k
        if c == 0:
            return base + r, n
        base, top = base + (r << c), base + ((r + 1) << c)
        left = left.where((F.col("flow") >= base) & (F.col("flow") < top))


def hot(cells: DataFrame, s_a, rounding: str = "floor", ties: str = "keep") -> DataFrame:
    """o, d, t of hot cells; ties at the threshold stay, or with ties='cut' go by (flow desc, o, d, t). The cells are read
    more than once: pass a table."""
    floor, n = minsup(cells, s_a, rounding)
    if ties == "keep":
        return cells.where(F.col("flow") >= floor).select("o", "d", "t")
    share = Fraction(str(s_a)) * n
    return cells.orderBy(F.desc("flow"), "o", "d", "t").limit(max(1, int(share) if rounding == "floor" else -int(-share // 1))).select("o", "d", "t")
