"""The k blocks with most hot cells at each level, in the total order (cnt desc, key)."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..durable import durable
from .mine import KEY, MODES, Index, count, extend, seed, together


def order():
    return [F.desc("cnt"), "o", "d", "t_lo", "t_hi"]


def best(counted: DataFrame, k: int) -> DataFrame:
    return durable(counted.select(*KEY, "cnt", "card").orderBy(*order()).limit(k))


def theta(top: DataFrame, k: int) -> int:
    """The k-th largest cnt so far; -1 while there are fewer."""
    last = top.agg(F.count("*").alias("n"), F.min("cnt").alias("c")).first()
    return last.c if last.n == k else -1


def room() -> dict[str, Column]:
    """The most hot cells that an extension of a dimension can add."""
    t, o, d = F.col("t_hi") - F.col("t_lo") + 1, F.size("o"), F.size("d")
    return {"o": d * t, "d": o * t, "t": o * d}


def waves(front: DataFrame, size: int, first: int) -> list[tuple[int, int]]:
    """(least, most) cnt of each wave, best first, each about twice the last; from a histogram of cnt, at most one row for
    each possible count."""
    out, held, want, top = [], 0, max(1, first), None
    for r in front.groupBy("cnt").agg(F.count("*").alias("n")).orderBy(F.desc("cnt")).toLocalIterator():
        top, held = r.cnt if top is None else top, held + r.n
        if held >= want:
            out.append((r.cnt, top))
            want, held, top = want * 2, 0, None
    return out + ([(0, top)] if held else [])


def by_bound(parts: dict, ix: Index, k: int, bounder) -> DataFrame:
    """Candidates that can be among the k best: those with the k largest upper bounds are counted first, and any whose bound
    stays below the k-th of these counts cannot."""
    capped = {x: durable(bounder(p.dropDuplicates(KEY))) for x, p in parts.items()}
    some = together(capped.values()).withColumn("most", F.col("cnt") + F.col("ub")).dropDuplicates(KEY).orderBy(F.desc("most"), *KEY).limit(k)
    counted = ix.whole(some.select(*KEY))
    floor = theta(durable(counted), k)
    return {x: p.where(F.col("cnt") + F.col("ub") >= floor).drop("ub") for x, p in capped.items()}


def enumerate_top(hot, graph, slots: int, k: int | None, max_level: int, mode: str = "threshold", bounds=None, domain=None, k_fraction: float | None = None):
    """mode: 'plain' (naive), 'full' (naive with the counting optimisations, and the prefix bound against the k-th best),
    'threshold' (gain caps and waves). With k_fraction, a level keeps that share of its candidates, rounded up.

    A parent with cnt c adds at most |D||T|, |O||T| or |O||D| hot cells by an origin, destination or slot; a side whose
    cap stays below the k-th best so far cannot matter. Parents go in geometric waves by cnt, so that bound rises early.
    From level 3 nothing can be skipped: every parent has cnt 1 and cap 2, and the k-th best is never above 2.
    Returns (blocks with level, stats)."""
    if (k is None) == (k_fraction is None) or k_fraction is not None and mode == "threshold":
        raise ValueError("either k or k_fraction; a fraction is known only after all candidates, so not with 'threshold'")
    ix = Index(durable(hot), graph, slots, mode != "plain")
    cols = [*KEY, "cnt", "card"]
    front, out, stats, memo, level = durable(seed(ix.hot)), [], [], None, 3
    counting = "packed" if mode == "threshold" and ix.fits else ("plain" if mode in ("plain", "threshold") else "memo_skip_nbr")
    bounder = ix.bounder() if mode == "full" and k is not None else None
    while level <= max_level and (size := front.count()):
        out.append(front.select(F.lit(level).alias("level"), *cols))
        if mode != "threshold":
            parts = extend(front, ix, bounds, MODES.index(counting) >= 3, domain)
            parts = by_bound(parts, ix, k, bounder) if bounder else parts
            counted, memo, work = count(parts, ix, counting, memo)
            keep = k if k is not None else -(-counted.count() * int(k_fraction * 10**9) // 10**9)
            front = best(counted, keep)
            stats.append({"level": level, "parents": size, **work})
        else:
            top, floor, skipped = None, -1, 0
            cuts = waves(front, size, k // 8)
            for i, (least, most) in enumerate(cuts):
                wave = front.where(F.col("cnt").between(least, most))
                # what a parent of this wave or a later one can reach at most
                cap = front.where(F.col("cnt") <= most).agg(F.max(F.col("cnt") + F.greatest(*room().values())).alias("cap")).first().cap if floor >= 0 else None
                if cap is not None and cap < floor:
                    skipped = front.where(F.col("cnt") <= most).count()
                    break
                parts = {x: extend(wave.where(F.col("cnt") + gain >= floor), ix, bounds, True, domain)[x] for x, gain in room().items()}
                counted = count(parts, ix, counting, None)[0].select(cols)
                top = best(counted if top is None else counted.unionByName(top).dropDuplicates(KEY), k)
                floor = theta(top, k) if i + 1 < len(cuts) else floor
            stats.append({"level": level, "parents": size, "parents_skipped": skipped, "theta": floor, "waves": len(cuts)})
            front = top
        level += 1
    df = out[0] if out else seed(ix.hot).select(F.lit(3).alias("level"), *cols)
    return together([df, *out[1:]]), stats


def top_per_level(blocks: DataFrame, k: int) -> DataFrame:
    """The k first blocks of each level; a level's ranking is its own, and holds at most k rows a task before it."""
    w = Window.partitionBy("level").orderBy(*order())
    return blocks.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)
