"""BPE encoding and decoding (operator 8).

Every word keeps one contiguous array of part boundaries with the rank of each adjacent pair beside it; the loop scans
for the smallest rank, deletes that boundary and refreshes the two ranks around it. Words longer than SHORT parts use a
heap over the same ranks, so one very long word costs n log n. Null text encodes as the empty text; ties between equal
ranks go to the leftmost pair; repeated rows give repeated results; an empty table gives an empty table.
"""
from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from array import array

import regex
from pyspark.sql import DataFrame

SHORT, CACHE = 96, 200_000
_COMMON = regex.compile(r"[^\x00-ɏ‐-‧€]")


def _byte_chars() -> list[str]:
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(spare)) for b in range(256)]


class WordBpe:
    """Encoder and decoder for one vocabulary file of the tokenizers library (byte letters, word-end mark)."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.path, self.vocab = path, spec["model"]["vocab"]
        self.end = spec["model"]["end_of_word_suffix"] or ""
        self.rank = {tuple(m.split(" ") if isinstance(m, str) else m): i for i, m in enumerate(spec["model"]["merges"])}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.token = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")")
        self.split = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        self.letters, self.words, self._library = _byte_chars(), {}, None

    def parts(self, letters: list[str]) -> list[str]:
        """Merge the letters of one word."""
        return self._scan(letters) if len(letters) <= SHORT else self._heap(letters)

    def _scan(self, parts: list[str]) -> list[str]:
        rank, none = self.rank.get, len(self.rank)
        ranks = [rank(pair, none) for pair in zip(parts, parts[1:])]
        while ranks and (low := min(ranks)) < none:
            i = ranks.index(low)
            parts[i] += parts.pop(i + 1)
            del ranks[i]
            if i < len(ranks):
                ranks[i] = rank((parts[i], parts[i + 1]), none)
            if i:
                ranks[i - 1] = rank((parts[i - 1], parts[i]), none)
        return parts

    def _heap(self, parts: list[str]) -> list[str]:
        n, rank = len(parts), self.rank.get
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        queue = [(r, i, parts[i], parts[i + 1]) for i in range(n - 1) if (r := rank((parts[i], parts[i + 1]))) is not None]
        heapq.heapify(queue)
        while queue:
            _, i, left, right = heapq.heappop(queue)
            j = after[i] if parts[i] == left else -1
            if j < 0 or parts[j] != right:
                continue
            parts[i], parts[j], after[i] = left + right, "", after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for a, b in ((before[i], i), (i, after[i])):
                if a >= 0 and b >= 0 and (r := rank((parts[a], parts[b]))) is not None:
                    heapq.heappush(queue, (r, a, parts[a], parts[b]))
        return [p for p in parts if p]

    def word(self, word: str) -> bytes:
        """Packed ids of one pre-token; short words are remembered, in a table that is emptied when full."""
        if (ids := self.words.get(word)) is None:
            letters = [self.letters[b] for b in word.encode()]
            letters[-1] += self.end
            ids = array("I", [self.vocab[p] for p in self.parts(letters)]).tobytes()
            if len(word) <= SHORT:
                if len(self.words) >= CACHE:
                    self.words.clear()
                self.words[word] = ids
        return ids

    def pretokens(self, text: str) -> list[str]:
        if _COMMON.search(text):  # rarer scripts: the file's own rules for letters and case, as its library applies them
            if self._library is None:
                from tokenizers import Tokenizer

                self._library = Tokenizer.from_file(self.path)
            lib = self._library
            clean, back = lib.normalizer.normalize_str(text), {c: b for b, c in enumerate(self.letters)}
            return [bytes(back[c] for c in w).decode() for w, _ in lib.pre_tokenizer.pre_tokenize_str(clean)]
        return self.split.findall(unicodedata.normalize("NFC", text).replace("Σ", "σ").lower())

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        out, known, word = [], self.words, self.word
        for piece in self.cut.split(text or ""):
            if piece in self.special:
                out.append(array("I", [self.special[piece]]).tobytes())
            elif piece:
                out.extend(known.get(w) or word(w) for w in self.pretokens(piece))
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        return " ".join(map(self.token.__getitem__, array("I", ids)))


_LOADED: dict[str, WordBpe] = {}


def codec(path: str) -> WordBpe:
    if path not in _LOADED:
        _LOADED[path] = WordBpe(path)
    return _LOADED[path]


def encode_documents(docs: DataFrame, path: str, digests_only: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, and unless digests_only the ids and the decoded text.

    One pass, no shuffle; a worker holds one Arrow batch and the word table."""
    extra = "" if digests_only else ", ids array<bigint>, decoded string"

    def run(batches):
        import pyarrow as pa

        bpe = codec(path)
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part, rows = b.slice(at, 512), []
                for doc, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    ids = bpe.encode(text)
                    back = bpe.decode(ids)
                    row = {"doc_id": doc, "n_tokens": len(ids) // 4, "ids_sha256": hashlib.sha256(ids).hexdigest(), "decoded_sha256": hashlib.sha256(back.encode()).hexdigest()}
                    rows.append(row if digests_only else row | {"ids": list(array("I", ids)), "decoded": back})
                kinds = [("doc_id", part.schema.field(0).type), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())]
                kinds += [] if digests_only else [("ids", pa.list_(pa.int64())), ("decoded", pa.string())]
                yield pa.RecordBatch.from_pylist(rows, schema=pa.schema(kinds))

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string{extra}")
