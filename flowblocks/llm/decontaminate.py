"""Benchmark decontamination (operator 7) by template canonicalisation.

Words become typed placeholders where they are numbers, units after a number, or names (a capital inside a sentence; a run
of names is one). Windows of WINDOW canonical words, at least LITERAL of them literal, are hashed, and document and benchmark windows
meet in a hash join. The key holds the template and the pattern of its slots (which of them have equal values), so a
window is met exactly where slot values pair off one to one: numbers and names may be others, but the same ones stay the same. An item
with fewer words is one window, if it has SHORTEST words or more. A capitalised word that opens a sentence may be a name or
not: an item's windows are hashed under every choice, a document's with all such words literal and with all as names. An
item without such a window, short or of few literals, is met where all its words stand in a document, values included, as one
window.

Ahead of the join a bitmap of fixed size over the benchmark's hashes, of any number of items, turns most document windows
away. Null and empty texts meet nothing, whatever their length; a null doc_id meets nothing; rows of one doc_id or item_id
are one document or item; other columns are not read; an empty benchmark leaves every document clean.
"""
from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch
from .word_stream import mix, windows, words

WINDOW, LITERAL, SHORTEST, BITMAP, CHUNKS = 13, 8, 6, 25, 64
_SPLIT = np.ones(256, bool)
_SPLIT[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False
_STOP = np.zeros(256, bool)
_STOP[[*b".!?:;\n\r\""]] = True
#: Fixed units of measure.
UNITS = "mm cm m km in ft yd mi mg g kg lb oz ml l s sec min h hr hours minutes seconds days weeks months years km/h mph hz khz mhz ghz w kw kwh v a j kj cal kcal usd eur dollars euros cents percent meters metres miles kilometers kilometres grams kilograms pounds liters litres".split()
_UNIT = np.unique(words(" ".join(UNITS).encode(), _SPLIT)[0])
_NUM, _NAME, _UNITS = (np.uint64(x) for x in (0x1111, 0x2222, 0x3333))


def canonical(text: str | None):
    """(words' hashes, number or unit or name placeholder of each or 0, mask of literals that may be names as they open a sentence)."""
    raw = (text or "").encode()
    h, s, e = words(raw, _SPLIT)
    kind = np.zeros(len(h), np.uint64)
    if not len(h):
        return h, kind, np.zeros(0, bool)
    b = np.frombuffer(raw, np.uint8)
    first = b[s]
    number = (first >= 48) & (first <= 57)
    second = b[np.minimum(s + 1, len(b) - 1)]
    name = (first >= 65) & (first <= 90) & (e - s > 1) & (second >= 97) & (second <= 122)
    at = np.flatnonzero(name)
    stops = np.flatnonzero(_STOP[b])  # a capital after one of these, or in front, opens a sentence
    opens = at[(at == 0) | (np.searchsorted(stops, s[at]) > np.searchsorted(stops, e[at - 1]))]
    name[opens] = False
    after = np.flatnonzero(number[:-1]) + 1
    kind[number], kind[name] = _NUM, _NAME
    after = after[kind[after] == 0]
    kind[after[np.isin(h[after], _UNIT)]] = _UNITS
    maybe = np.zeros(len(h), bool)
    maybe[opens[kind[opens] == 0]] = True
    return h, kind, maybe


def reading(h: np.ndarray, kind: np.ndarray):
    """(template hash, value hash, literal mask, first word) of the canonical words: a run of names is one."""
    name = kind == _NAME
    begin = np.ones(len(h), bool)
    begin[1:] = ~(name[1:] & name[:-1])
    at = np.flatnonzero(begin)
    value = h[at]
    if len(at) < len(h):
        place = np.arange(len(h)) - np.repeat(at, np.diff(np.append(at, len(h))))
        runs = np.add.reduceat(mix(h + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)), at)
        value = np.where(name[at], runs, value)
    elif name.any():
        value = np.where(name, mix(h), h)
    k = kind[at]
    return np.where(k == 0, h[at], k), value, k == 0, at


def pattern(values: np.ndarray, literal: np.ndarray) -> int:
    """A hash of which slots hold equal values."""
    seen: dict = {}
    return hash_of([seen.setdefault(v, len(seen)) for v in values[~literal].tolist()])


def hash_of(numbers) -> int:
    return int(windows(np.array([len(numbers), *numbers], np.uint64), len(numbers) + 1)[0].astype(np.int64))


def item_windows(text: str | None):
    """(size, template, pattern, values, first word) of an item's windows with enough literals, under every reading."""
    h, kind, maybe = canonical(text)
    out = set()
    for i in range(len(h)):
        end = min(len(h), i + 4 * WINDOW)
        spare = np.flatnonzero(maybe[i:end]) + i
        for k in range(min(len(spare), WINDOW - LITERAL) + 1):
            for names in combinations(spare.tolist(), k):
                own = kind[i:end].copy()
                own[np.array(names, np.int64) - i] = _NAME
                if i and own[0] == _NAME and kind[i - 1] == _NAME:
                    continue
                t, v, literal, at = reading(h[i:end], own)
                n = min(WINDOW, len(t))
                if n < SHORTEST or n < WINDOW and (i or end < len(h)) or literal[:n].sum() < min(LITERAL, n - 2):
                    continue
                if names and len(at) > n and names[-1] - i >= at[n]:
                    continue  # the choice lies behind the window
                out.add((n, int(windows(t[:n], n)[0].astype(np.int64)), pattern(v[:n], literal[:n]), int(windows(v[:n], n)[0].astype(np.int64)), i))
    return sorted(out)


def item_rows(benchmark: DataFrame) -> DataFrame:
    """item_id, n, key, pattern, value, at, size: windows (size 0), and of items without any their first words and their size."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            rows = []
            for item, text in zip(b.column(0).to_pylist(), b.column(1)):
                found = item_windows(text.as_py())
                rows += [(item, *w, 0) for w in found]
                h = canonical(text.as_py())[0]
                if not found and len(h):
                    n = min(WINDOW, len(h))
                    rows.append((item, n, int(windows(h[:n], n)[0].astype(np.int64)), 0, int(windows(h, len(h))[0].astype(np.int64)), 0, len(h)))
            cols = list(zip(*rows)) or [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["item_id", "n", "key", "pattern", "value", "at", "size"])

    kept = benchmark.select(F.col("item_id").cast("bigint"), "text").where("text is not null and item_id is not null")
    return kept.mapInArrow(run, "item_id bigint, n bigint, key bigint, pattern bigint, value bigint, at bigint, size bigint").distinct()


def bitmap(items: DataFrame) -> np.ndarray:
    """A bit for the top BITMAP bits of every key, gathered in CHUNKS pieces: of one size for any benchmark."""
    width = (1 << BITMAP) // CHUNKS

    def mark(table):
        import pyarrow as pa

        bits = np.zeros(width, bool)
        bits[table.column("at").to_numpy()] = True
        return pa.table({"chunk": pa.array([table.column("chunk")[0].as_py()], pa.int32()), "part": pa.array([np.packbits(bits).tobytes()], pa.binary())})

    place = F.call_function("shiftrightunsigned", F.col("key"), F.lit(64 - BITMAP))
    rows = items.select(F.floor(place / width).cast("int").alias("chunk"), (place % width).alias("at")).distinct()
    out = np.zeros((CHUNKS, width // 8), np.uint8)
    for r in rows.groupBy("chunk").applyInArrow(mark, "chunk int, part binary").collect():
        out[r.chunk] = np.frombuffer(r.part, np.uint8)
    return out.ravel()


def met(w: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Places of w whose hash may be known."""
    at = w >> np.uint64(64 - BITMAP)
    return np.flatnonzero(bits[(at >> np.uint64(3)).astype(np.int64)] >> (np.uint8(7) - (at & np.uint64(7)).astype(np.uint8)) & np.uint8(1))


def hits(docs: DataFrame, items: DataFrame) -> DataFrame:
    """doc_id, n, key, pattern, value, at, whole: windows of the documents that may be met."""
    sizes = [tuple(r) for r in items.select("n", (F.col("size") > 0).alias("whole")).distinct().collect()]  # at most 2 x WINDOW
    shared = docs.sparkSession.sparkContext.broadcast((bitmap(items), sorted(n for n, whole in sizes if not whole), sorted(n for n, whole in sizes if whole)))

    def run(batches):
        import pyarrow as pa

        bits, spans, fronts = shared.value
        for b in batches:
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1)):
                h, kind, maybe = canonical(text.as_py())
                for own in [kind] + [np.where(maybe, _NAME, kind)] * bool(maybe.any()):
                    t, v, literal, at = reading(h, own)
                    for n in spans:
                        w = windows(t, n)
                        for i in met(w, bits).tolist():
                            rows.append((doc, n, int(w[i].astype(np.int64)), pattern(v[i : i + n], literal[i : i + n]), int(windows(v[i : i + n], n)[0].astype(np.int64)), int(at[i]), False))
                for n in fronts:
                    w = windows(h, n)
                    rows += [(doc, n, int(w[i].astype(np.int64)), 0, 0, i, True) for i in met(w, bits).tolist()]
            cols = list(zip(*rows)) or [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], b.schema.field(0).type), *(pa.array(c, pa.int64()) for c in cols[1:6]), pa.array(cols[6], pa.bool_())], ["doc_id", "n", "key", "pattern", "value", "at", "whole"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").where("doc_id is not null").mapInArrow(run, f"doc_id {kind}, n bigint, key bigint, pattern bigint, value bigint, at bigint, whole boolean")


def whole_items(docs: DataFrame, cand: DataFrame) -> DataFrame:
    """Of the places (doc_id, at, item_id, size, value) those where all words of the item stand."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        import pyarrow as pa

        for b in batches:
            rows = []
            for doc, text, places in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist()):
                h = canonical(text.as_py())[0]
                rows += [(doc, x["item_id"], x["at"]) for x in places if len(h) >= x["at"] + x["size"] and int(windows(h[x["at"] : x["at"] + x["size"]], x["size"])[0].astype(np.int64)) == x["value"]]
            cols = list(zip(*rows)) or [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], b.schema.field(0).type), *(pa.array(c, pa.int64()) for c in cols[1:])], ["doc_id", "item_id", "at"])

    of = cand.groupBy("doc_id").agg(F.collect_set(F.struct("at", "item_id", "size", "value")).alias("places"))
    return docs.select("doc_id", "text").join(of, "doc_id").select("doc_id", "text", "places").mapInArrow(run, f"doc_id {kind}, item_id bigint, at bigint")


def match(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, n_windows met consistently, n_exact of them with the same values."""
    disk = Scratch(docs.sparkSession)
    items = disk.keep("items", item_rows(benchmark))
    found = disk.keep("hits", hits(docs, items))
    known = items.where("size = 0").select("item_id", "n", "key", "pattern", F.col("value").alias("own"), F.col("at").alias("item_at"))
    slots = found.where("not whole").join(known, ["n", "key", "pattern"]).select("doc_id", "item_id", "at", "item_at", (F.col("value") == F.col("own")).alias("same"))
    fronts = found.where("whole").select("doc_id", "n", "key", "at").join(items.where("size > 0").select("item_id", "n", "key", "value", "size"), ["n", "key"])
    entire = whole_items(docs, fronts).select("doc_id", "item_id", "at", F.lit(0).cast("bigint").alias("item_at"), F.lit(True).alias("same"))
    # a window counts once, however its words are read
    once = slots.union(entire).groupBy("doc_id", "item_id", "at", "item_at").agg(F.max("same").alias("same"))
    return once.groupBy("doc_id", "item_id").agg(F.count("*").alias("n_windows"), F.count_if("same").alias("n_exact"))


def report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row per document that meets the benchmark: doc_id, n_items, item_ids, n_windows, n_exact."""
    m = match(docs, benchmark)
    return m.groupBy("doc_id").agg(F.count("*").alias("n_items"), F.array_join(F.array_sort(F.collect_list("item_id")), ",").alias("item_ids"), F.sum("n_windows").alias("n_windows"), F.sum("n_exact").alias("n_exact"))


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents that meet nothing; rows without doc_id stay."""
    return docs.join(match(docs, benchmark).select("doc_id").distinct(), "doc_id", "left_anti").select(docs.columns)
