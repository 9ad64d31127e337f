"""Closed-form worst cases, in exact integers."""
from __future__ import annotations

from math import comb, log2


def windows(slots: int) -> int:
    """Runs of consecutive slots."""
    return slots * (slots + 1) // 2


def levelwise(regions: int, slots: int) -> int:
    """Blocks that could exist: pairs of disjoint non-empty sides times the runs of slots (any set taken as connected)."""
    sides = sum(comb(regions, k) * (2 ** (regions - k) - 1) for k in range(1, regions))
    return sides * windows(slots)


def bounded(regions: int, slots: int, bounds: tuple[int, int, int]) -> int:
    bo, bd, bt = bounds
    sides = sum(comb(regions, i) * comb(max(0, regions - i), j) for i in range(1, bo + 1) for j in range(1, bd + 1))
    return sides * sum(max(0, slots - k + 1) for k in range(1, bt + 1))


def partners(regions: int) -> int:
    """Entries of the origin and destination partner sets."""
    return 2 * regions * (regions - 1)


def prefix(regions: int, slots: int) -> int:
    return (regions + 1) ** 2 * (slots + 1)


def pool(regions: int, size: int) -> int:
    return regions * size


def sampling(draws: int, shape: tuple[int, int, int]) -> int:
    return draws * shape[0] * shape[1] * shape[2]


def combinations(regions: int, slots: int, shape: tuple[int, int, int]) -> int:
    return regions * regions * max(0, slots - shape[2] + 1)


def weighted(regions: int, slots: int, shape: tuple[int, int, int], keep: int) -> int:
    """Scoring every combination into the keep best, then verifying them."""
    return int(combinations(regions, slots, shape) * max(1.0, log2(max(2, keep)))) + keep * shape[0] * shape[1] * shape[2]


def table(regions: int, slots: int, trips: int) -> list[tuple[str, int]]:
    """(formula, steps) for a network of these sizes, with blocks of up to three a side, shapes of four and a draw a trip."""
    return [("levelwise", levelwise(regions, slots)), ("bounded", bounded(regions, slots, (3, 3, 3))), ("partners", partners(regions)), ("prefix", prefix(regions, slots)), ("pool", pool(regions, 4)), ("sampling", sampling(trips, (4, 4, 4))), ("combinations", combinations(regions, slots, (4, 4, 4)))]


def rows(sizes):
    """formula, steps for a frame of (regions, slots, trips)."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            found = [x for r in batch.to_pylist() for x in table(r["regions"], r["slots"], r["trips"])]
            yield pa.RecordBatch.from_arrays([pa.array([f for f, _ in found], pa.string()), pa.array([k for _, k in found], pa.int64())], ["formula", "steps"])

    return sizes.select("regions", "slots", "trips").mapInArrow(run, "formula string, steps bigint")
