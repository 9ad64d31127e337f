"""Token counts (operator 6) by offset-mapped attribution.

A document is encoded once as a whole with a byte-level vocabulary; token byte spans follow from token lengths, and an
interval join in order (binary search of span starts among section starts) gives tokens to sections. A token that
crosses a boundary goes by an explicit rule: `start` (the section of its first byte), `end` (of its last byte) or
`majority` (most bytes, ties to the earlier). Sections are the lines of a text with their line ends, or given fields. Null and
empty texts have no token and one empty section.
"""
from __future__ import annotations

import base64
import hashlib

import numpy as np
from pyspark.sql import DataFrame

_LOADED: dict = {}


def encoder(path: str, pattern: str):
    """(encoding, bytes of each token id)."""
    if path not in _LOADED:
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        size = np.zeros(max(ranks.values()) + 1, np.int64)
        for token, i in ranks.items():
            size[i] = len(token)
        _LOADED[path] = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}), size
    return _LOADED[path]


def attribute(ids, size: np.ndarray, starts: np.ndarray, rule: str = "start") -> tuple[np.ndarray, int]:
    """(tokens of each section, tokens that cross a boundary); starts: first byte of each section, ascending from 0."""
    width = size[np.asarray(ids, np.int64)] if len(ids) else np.zeros(0, np.int64)
    end = np.cumsum(width)
    first = np.searchsorted(starts, end - width, "right") - 1
    last = np.searchsorted(starts, end - 1, "right") - 1
    to = first
    if rule == "end":
        to = last
    elif rule == "majority":
        to = first.copy()
        for i in np.flatnonzero(first != last):
            cuts = np.clip(np.append(starts[first[i] : last[i] + 1], end[i]), end[i] - width[i], end[i])
            to[i] = first[i] + int(np.argmax(np.diff(cuts)))
    elif rule != "start":
        raise ValueError(rule)
    return np.bincount(to, minlength=len(starts)), int((first != last).sum())


def line_starts(raw: bytes) -> np.ndarray:
    ends = np.flatnonzero(np.frombuffer(raw, np.uint8) == 10) + 1
    return np.concatenate([[0], ends[ends < len(raw)]])


def count_tokens(docs: DataFrame, path: str, pattern: str, rule: str = "start", sections: bool = False) -> DataFrame:
    """doc_id, n_tokens, n_sections, n_crossing, max_section, section_sha256 (of the counts, comma-joined); with sections, their counts too."""

    def run(batches):
        import pyarrow as pa

        enc, size = encoder(path, pattern)
        for b in batches:
            rows, counts = [], []
            for text in b.column(1):
                text = text.as_py() or ""
                per, crossing = attribute(enc.encode_ordinary(text), size, line_starts(text.encode()), rule)
                rows.append((int(per.sum()), len(per), crossing, int(per.max()), hashlib.sha256(",".join(map(str, per.tolist())).encode()).hexdigest()))
                counts.append(per.tolist())
            cols = list(zip(*rows)) or [[]] * 5
            out = [b.column(0), *(pa.array(c, pa.int64()) for c in cols[:4]), pa.array(cols[4], pa.string())] + ([pa.array(counts, pa.list_(pa.int64()))] if sections else [])
            yield pa.RecordBatch.from_arrays(out, ["doc_id", "n_tokens", "n_sections", "n_crossing", "max_section", "section_sha256", "sections"][: len(out)])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_tokens bigint, n_sections bigint, n_crossing bigint, max_section bigint, section_sha256 string" + ", sections array<bigint>" * sections)
