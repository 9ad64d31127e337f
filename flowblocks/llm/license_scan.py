"""License scan (operator 2), DataFrame functions only: ordered signature rules over a text's words.

A text's words are joined by single blanks, so a rule is a regular expression over whole words and its places are word
intervals. A rule runs only where its keyword occurs. Detections are ordered by start, longer first, then priority; one
that lies inside an earlier one of equal or higher priority is suppressed. The four base phrases are rules too; their
places are counted before suppression and their labels always stay. Null or empty texts have no word and no label; work is
near linear in a very long text; every row has its own result, repeated doc_ids and null ones too; other columns are not
read; an empty table gives an empty table.
"""
from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: What lies between words once A-Z are lower-cased.
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]++"
#: Fixed phrases of the contract.
BASE = [("gpl", "gnu general public license"), ("apache", "apache license"), ("cc-by", "cc by"), ("mit", "mit license")]
LEVELS, BLOCK = 4, 256
#: Marks around a match; no word holds them.
BEGIN, END = "\x01", "\x02"


def rules() -> list[tuple[str, str, str, int, float]]:
    """(label, keyword, pattern over words, priority, confidence), most specific first, made from families and forms."""
    out = []
    ver = lambda *v: [(x, x.replace(".", " ")) for x in v]
    for family, name, versions in (
        ("gpl", "(?:gnu )?general public license", ver("1.0", "2.0", "3.0")), ("lgpl", "(?:gnu )?(?:lesser|library) general public license", ver("2.0", "2.1", "3.0")),
        ("agpl", "(?:gnu )?affero general public license", ver("1.0", "3.0")), ("gfdl", "(?:gnu )?free documentation license", ver("1.1", "1.2", "1.3")),
        ("apache", "apache (?:software )?license", ver("1.0", "1.1", "2.0")), ("mpl", "mozilla public license", ver("1.0", "1.1", "2.0")), ("epl", "eclipse public license", ver("1.0", "2.0")),
        ("cddl", "common development and distribution license", ver("1.0", "1.1")), ("eupl", "european union public licen[cs]e", ver("1.0", "1.1", "1.2")), ("artistic", "artistic license", ver("1.0", "2.0")),
        ("osl", "open software license", ver("1.0", "2.0", "3.0")), ("afl", "academic free license", ver("2.0", "2.1", "3.0")), ("cpl", "common public license", ver("1.0")), ("bsl", "boost software license", ver("1.0")), ("psf", "python software foundation license", ver("2.0")),
    ):
        key = name.split("(?:gnu )?")[-1].split(" ")[0].strip("(?:").split("|")[0]
        key = {"lesser": "public", "licen[cs]e": "public"}.get(key, key)
        for label, words in versions:
            short = words[:-2] if words.endswith(" 0") else words
            for lead, conf in (("(?:licensed|released|distributed|available|redistribute it) (?:\\w+ ){0,6}", 1.0), ("", 0.9)):
                out.append((f"{family}-{label}", key, f"{lead}{name} (?:as published by the free software foundation )?(?:(?:either )?version |v |v)?(?:{words}|{short}) ", 3, conf))
                out.append((f"{family}-{label}-or-later", key, f"{lead}{name} (?:\\w+ ){{0,8}}?(?:version )?(?:{words}|{short}) (?:of the license )?or (?:at your option )?any later version ", 4, conf))
            out.append((f"{family}-{label}", family, f"{family} v?(?:{words}|{short}) ", 2, 0.8))
        out.append((family, key, f"{name} ", 1, 0.7))
    for mark, long in (("by", "attribution"), ("by nc", "attribution non ?commercial"), ("by sa", "attribution share ?alike"), ("by nd", "attribution no ?deriv(?:ative)?s"), ("by nc sa", "attribution non ?commercial share ?alike"), ("by nc nd", "attribution non ?commercial no ?deriv(?:ative)?s")):
        tag = "cc-" + mark.replace(" ", "-")
        for v in ("1 0", "2 0", "2 5", "3 0", "4 0"):
            out.append((f"{tag}-{v.replace(' ', '.')}", "cc", f"cc {mark} {v} ", 3, 1.0))
            out.append((f"{tag}-{v.replace(' ', '.')}", "commons", f"creative commons {long} (?:\\w+ ){{0,3}}?{v} ", 3, 1.0))
        out += [(tag, "cc", f"cc {mark} ", 1, 0.8), (tag, "commons", f"creative commons {long} ", 1, 0.8)]
    for label, key, pattern in (
        ("mit", "permission", "permission is hereby granted free of charge to any person obtaining a copy "), ("isc", "permission", "permission to use copy modify and or distribute this software for any purpose "),
        ("bsd", "redistribution", "redistribution and use in source and binary forms with or without modification are permitted "), ("bsd-3-clause", "neither", "neither the name of (?:\\w+ ){1,12}?nor the names of its contributors "),
        ("unlicense", "unencumbered", "free and unencumbered software released into the public domain "), ("wtfpl", "wtfpl", "wtfpl "), ("zlib", "misrepresented", "the origin of this software must not be misrepresented "),
        ("cc0-1.0", "cc0", "cc0 (?:1 0 )?"), ("public-domain", "domain", "(?:in|into|to) the public domain "), ("proprietary", "reserved", "all rights reserved "), ("bsd-2-clause", "bsd", "bsd 2 clause "), ("bsd-3-clause", "bsd", "bsd 3 clause "),
        ("mit", "mit", "(?:released|licensed|available|distributed) under (?:the )?mit license "), ("isc", "isc", "isc license "), ("unlicense", "unlicense", "the unlicense "), ("spdx", "spdx", "spdx license identifier \\w+ "),
    ):
        out.append((label, key, pattern, 2, 0.9))
    return sorted(dict.fromkeys(out), key=lambda r: -r[3])


HIT = "array<struct<label:string,s:bigint,e:bigint,priority:int,confidence:double>>"


def places(norm: Column, pattern: Column) -> Column:
    """Word intervals of a pattern's matches, read off marks set around them; norm begins and ends with a blank."""
    text = F.concat(F.lit("(?<= )"), pattern)
    marked = F.split(F.regexp_replace(norm, text, F.lit(f"{BEGIN}$0{END}")), " ", -1)
    at = lambda mark: F.filter(F.transform(marked, lambda w, i: F.when(F.contains(w, F.lit(mark)), i.cast("bigint") - 1)), lambda i: i.isNotNull())
    found = F.zip_with(at(BEGIN), at(END), lambda s, e: F.struct(s.alias("s"), e.alias("e")))
    return F.when(F.rlike(norm, text), found).otherwise(F.array().cast("array<struct<s:bigint,e:bigint>>"))


def due(norm: Column, table: list[tuple[str, str, str, int, float]]) -> Column:
    """The rules whose keyword occurs as a word. The table is one constant, so the plan does not grow with the rules; a
    keyword is looked up once for all its rules."""
    names = ("label", "pattern", "priority", "confidence")
    row = lambda r: F.struct(*[F.lit(x).alias(c) for c, x in zip(names, (r[0], *r[2:]))])
    keys = sorted({r[1] for r in table})
    known = F.array(*[F.struct(F.lit(f" {k} ").alias("key"), F.array(*[row(r) for r in table if r[1] == k]).alias("rules")) for k in keys])
    return F.flatten(F.transform(F.filter(known, lambda k: F.contains(norm, k["key"])), lambda k: k["rules"]))


def detections(norm: Column, table: list[tuple[str, str, str, int, float]]) -> Column:
    """Matches of the rules that are due."""
    named = lambda r: F.transform(places(norm, r["pattern"]), lambda x: F.struct(r["label"].alias("label"), x["s"].alias("s"), x["e"].alias("e"), r["priority"].alias("priority"), r["confidence"].alias("confidence")))
    return F.flatten(F.transform(due(norm, table), named)).cast(HIT)


def suppressed(found: Column) -> Column:
    """Without the detections inside an earlier one of equal or higher priority; one ordered pass with an end for each
    priority, in blocks, so that a text of very many detections is not copied for each of them."""
    order = F.array_sort(F.transform(found, lambda x: F.struct(x["s"].alias("s"), (-x["e"]).alias("m"), (-x["priority"]).alias("p"), x["label"].alias("label"), x["confidence"].alias("c"))))

    def keep(acc, x):
        inside = F.exists(F.slice(acc["ends"], -x["p"], F.lit(LEVELS)), lambda e: e >= -x["m"])
        ends = F.transform(acc["ends"], lambda e, i: F.when(i + 1 == -x["p"], F.greatest(e, -x["m"])).otherwise(e))
        one = F.struct(x["label"].alias("label"), x["s"].alias("s"), (-x["m"]).alias("e"), (-x["p"]).alias("priority"), x["c"].alias("confidence"))
        return F.struct(ends.alias("ends"), F.when(inside, acc["out"]).otherwise(F.array_append(acc["out"], one)).alias("out"))

    def block(acc, b):
        part = F.aggregate(F.slice(acc["order"], b * BLOCK + 1, F.lit(BLOCK)), F.struct(acc["ends"].alias("ends"), F.array().cast(HIT).alias("out")), keep)
        return F.transform(F.array(part), lambda p: F.struct(acc["order"].alias("order"), p["ends"].alias("ends"), F.array_append(acc["out"], p["out"]).alias("out")))[0]

    zero = F.struct(order.alias("order"), F.array(*[F.lit(-1).cast("bigint")] * LEVELS).alias("ends"), F.array().cast(f"array<{HIT}>").alias("out"))
    blocks = F.sequence(F.lit(0), F.floor((F.size(found) - 1) / BLOCK).cast("int"))
    return F.when(F.size(found) > 0, F.aggregate(blocks, zero, block, lambda acc: F.flatten(acc["out"]))).otherwise(F.array().cast(HIT))


def lowered(text: Column) -> Column:
    """A-Z in lower case. lower() changes other letters too, but of those only the Kelvin sign becomes an ASCII letter."""
    return F.when(F.contains(text, F.lit("\u212a")), F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).otherwise(F.lower(text))


def scan_licenses(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, base detections and kept detections; one pass without a shuffle."""
    base = [(label, phrase.split(" ")[0], f"{phrase} ", 1, 0.7) for label, phrase in BASE]
    bare = F.trim(F.regexp_replace(lowered(F.coalesce("text", F.lit(""))), GAP, " "))
    words = docs.select("doc_id", F.concat(F.lit(" "), bare, F.lit(" ")).alias("norm"))
    blanks = F.length("norm") - F.length(F.replace(F.col("norm"), F.lit(" "), F.lit("")))
    n_words = F.when(F.col("norm") == "  ", 0).otherwise(blanks - 1).cast("bigint").alias("n_words")
    found = words.select("doc_id", n_words, detections(F.col("norm"), base).alias("base"), detections(F.col("norm"), rules()).alias("more"))
    return found.select("doc_id", "n_words", "base", suppressed(F.concat("base", "more")).alias("kept"))


def report(docs: DataFrame) -> DataFrame:
    d = scan_licenses(docs)
    starts, tags = F.transform("base", lambda x: x["s"]), F.transform("base", lambda x: x["label"])
    join = lambda a: F.array_join(F.array_sort(F.array_distinct(a)), ",")
    return d.select(
        "doc_id", "n_words", F.size("base").cast("long").alias("n_base"), F.array_min(starts).alias("first_word"), F.array_max(starts).alias("last_word"), join(tags).alias("base_labels"),
        join(F.concat(tags, F.transform("kept", lambda x: x["label"]))).alias("labels"), F.coalesce(F.array_max(F.transform("kept", lambda x: x["confidence"])), F.lit(0.0)).alias("score"),
    )
