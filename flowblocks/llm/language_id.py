"""Language identification (operator 5): multinomial naive Bayes over hashed character n-grams.

Counts come from documents whose crc32(doc_id as text) mod 4 is not 2 and whose lang is not null; beyond
`per_language` of them in a language, a share chosen by a hash of doc_id trains (a documented bound, met in
expectation). Prediction sees the text alone. Null texts and texts without a letter are `und` with score 0; with no
labelled row every text is `und`. Ties go to the language that sorts first.
"""
from __future__ import annotations

import unicodedata

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ORDERS, BITS, PER_LANGUAGE, MAX_LANGUAGES, SLICE = (1, 2, 3), 16, 4000, 512, 1 << 20


def has_letter(text: str) -> bool:
    return text.isascii() and any(map(str.isalpha, text[:64])) or any(unicodedata.category(c)[0] == "L" for c in text)


def gram_stream(text: str, bits: int = BITS):
    """Bucket ids of all n-grams of the lower-cased text, in slices of bounded length that overlap by the n-gram reach."""
    for at in range(0, len(text), SLICE):
        c = np.frombuffer(text[at : at + SLICE + 2].lower().encode("utf-32-le"), "<u4").astype(np.uint32)
        n = min(SLICE, len(c))
        h = c * np.uint32(0x9E3779B1)
        yield (h[:n] ^ (h[:n] >> np.uint32(15))) >> np.uint32(32 - bits)
        for reach in range(1, max(ORDERS)):
            if len(c) <= reach:
                break
            h = (h[: len(c) - reach] ^ (h[: len(c) - reach] >> np.uint32(13))) * np.uint32(0x85EBCA6B) + c[reach:] * np.uint32(0xC2B2AE35)
            k = h[:n]
            yield (k ^ (k >> np.uint32(16))) >> np.uint32(32 - bits)


def is_held_out(col: str = "doc_id"):
    return F.crc32(F.col(col).cast("string").cast("binary")) % 4 == 2


def fit(docs: DataFrame, per_language: int = PER_LANGUAGE, bits: int = BITS, alpha: float = 0.5):
    """(languages, log-probability matrix [bucket, language], log priors)."""
    mine = docs.select("doc_id", "text", "lang").where(~F.coalesce(is_held_out(), F.lit(True)) & F.col("lang").isNotNull() & F.col("text").isNotNull())
    sizes = sorted((r[0], r[1]) for r in mine.groupBy("lang").count().limit(MAX_LANGUAGES + 1).collect())
    if len(sizes) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages")
    langs, n = [x for x, _ in sizes], np.array([c for _, c in sizes], float)
    if not langs:
        return [], np.zeros((1 << bits, 0), np.float32), np.zeros(0)
    share = F.create_map(*[x for lang, c in sizes for x in (F.lit(lang), F.lit(int(min(1.0, per_language / c) * (1 << 20))))])
    sample = mine.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < F.element_at(share, F.col("lang")))
    place = {x: i for i, x in enumerate(langs)}

    def count(batches):
        import pyarrow as pa

        total: dict[int, np.ndarray] = {}
        for b in batches:
            for text, lang in zip(b.column(0), b.column(1)):
                row = total.setdefault(place[lang.as_py()], np.zeros(1 << bits, np.int64))
                for grams in gram_stream(text.as_py(), bits):
                    row += np.bincount(grams, minlength=1 << bits)
        for lang, row in total.items():
            at = np.flatnonzero(row)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), lang, np.int32)), pa.array(at.astype(np.int32)), pa.array(row[at])], ["l", "b", "n"])

    got = sample.select("text", "lang").mapInArrow(count, "l int, b int, n bigint").groupBy("l", "b").agg(F.sum("n").alias("n")).toPandas()
    counts = np.full((1 << bits, len(langs)), alpha)
    counts[got.b, got.l] += got.n
    return langs, np.log(counts / counts.sum(0)).astype(np.float32), np.log(n / n.sum())


def predict(docs: DataFrame, model) -> DataFrame:
    """doc_id, lang_pred, score (posterior of the prediction). The matrix has 2^bits rows for each language, a fixed size."""
    spark, shared = docs.sparkSession, None
    shared = spark.sparkContext.broadcast(model)

    def run(batches):
        import pyarrow as pa

        langs, table, prior = shared.value
        for b in batches:
            pred, score = [], []
            for text in b.column(1):
                text = text.as_py()
                if not langs or text is None or not has_letter(text):
                    pred.append("und")
                    score.append(0.0)
                    continue
                grams = np.concatenate(list(gram_stream(text))) if len(text) <= SLICE else None
                if grams is not None and len(grams) < 1 << 14:
                    total = prior + table[grams].sum(0, dtype=np.float64)
                else:
                    total = prior.copy()
                    for g in gram_stream(text):
                        hits = np.bincount(g, minlength=len(table))
                        at = np.flatnonzero(hits)
                        total += hits[at] @ table[at].astype(np.float64)
                best = int(total.argmax())
                pred.append(langs[best])
                score.append(float(1 / np.exp(total - total[best]).sum()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(pred, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, lang_pred string, score double")


def identify(docs: DataFrame) -> DataFrame:
    out = predict(docs, fit(docs))
    return out.select("doc_id", F.coalesce(is_held_out(), F.lit(False)).alias("held_out"), "lang_pred", "score")
