"""Secret scan (operator 3): an incremental ledger of content-addressed blobs.

Every version of every path is addressed by the SHA-256 of its text (null: empty). Pairs of (blob, rule version) that
the ledger lacks are scanned once, on one representative row of the blob, and findings are joined back to all paths
with that content. Repeated rows share a blob; an empty table leaves the ledger as it was. Offsets are code points.
"""
from __future__ import annotations

import math
import re
import zlib
from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable

ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A | re.I)
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ACCESS, HEX = re.compile(r"AKIA[A-Z0-9]+"), re.compile(r"[0-9a-f]{16,}")
#: Rules that the method adds: (kind, keyword that must occur, pattern). Fixed formats of public services.
EXTRA = [
    ("github", "gh", re.compile(r"gh[pousr]_[A-Za-z0-9]{36,}")),
    ("slack", "xox", re.compile(r"xox[abprs]-[A-Za-z0-9-]{10,}")),
    ("jwt", "eyJ", re.compile(r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{5,}")),
    ("private_key", "-----BEGIN", re.compile(r"-----BEGIN (?:[A-Z]+ ){0,3}PRIVATE KEY-----")),
    ("google_api", "AIza", re.compile(r"AIza[A-Za-z0-9_-]{35}")),
    ("stripe", "_live_", re.compile(r"(?:sk|rk)_live_[A-Za-z0-9]{16,}")),
]
ENTROPIC = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{32,}={0,2}(?![A-Za-z0-9+/_=-])")


def entropy(s: str) -> float:
    return -sum(n / len(s) * math.log2(n / len(s)) for n in Counter(s).values())


def assign(text: str):
    low = text.lower()
    if any(k in low for k in KEYWORDS):
        yield from (("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= 12)


def access(text: str):
    if "AKIA" in text:
        yield from (("access", *m.span()) for m in ACCESS.finditer(text) if len(m[0]) >= 18)


def hexes(text: str):
    yield from (("hex", *m.span()) for m in HEX.finditer(text))


def services(text: str):
    for kind, key, pattern in EXTRA:
        if key in text:
            yield from ((kind, *m.span()) for m in pattern.finditer(text))


def entropic(text: str):
    for m in ENTROPIC.finditer(text):
        s = m[0]
        if any(map(str.isdigit, s)) and any(map(str.isupper, s)) and any(map(str.islower, s)) and entropy(s) >= 4.2:
            yield ("entropy", *m.span())


#: (rule, version, scanner); a new version makes every blob unseen for that rule alone.
RULES = [("assign", 1, assign), ("access", 1, access), ("hex", 1, hexes), ("services", 1, services), ("entropic", 1, entropic)]
ORDER = {k: i for i, k in enumerate(["assign", "access", "hex"])}
FINDING = "array<struct<kind:string,s:bigint,e:bigint>>"


def address(paths: DataFrame, path: str = "doc_id", text: str = "text") -> DataFrame:
    return paths.select(F.col(path).alias("path"), F.sha2(F.coalesce(F.col(text), F.lit("")).cast("binary"), 256).alias("blob"))


def unseen(versions: DataFrame, ledger: DataFrame | None, rules=None) -> DataFrame:
    """(path, blob, rules): one representative path for each blob and the rules its ledger entries lack."""
    rules = rules or RULES
    due = F.array(*[F.concat_ws("@", F.lit(r), F.lit(v)) for r, v, _ in rules])
    blobs = versions.groupBy("blob").agg(F.min("path").alias("path"))
    if ledger is None:
        return blobs.select("path", "blob", due.alias("rules"))
    seen = ledger.groupBy("blob").agg(F.collect_set("rule").alias("seen"))  # at most one entry a rule version
    return blobs.join(seen, "blob", "left").select("path", "blob", F.array_except(due, F.coalesce("seen", F.array().cast("array<string>"))).alias("rules")).where(F.size("rules") > 0)


def scan(paths: DataFrame, pending: DataFrame, path: str = "doc_id", text: str = "text", rules=None) -> DataFrame:
    """Ledger entries (blob, rule, findings) of the pending pairs; a row for each pair, found or not."""
    scanners = {f"{r}@{v}": f for r, v, f in rules or RULES}

    def run(batches):
        import pyarrow as pa

        kind = pa.list_(pa.struct([("kind", pa.string()), ("s", pa.int64()), ("e", pa.int64())]))
        for b in batches:
            blobs, names, found = [], [], []
            for body, blob, due in zip(b.column(0), b.column(1).to_pylist(), b.column(2).to_pylist()):
                body = zlib.decompress(body.as_py()).decode()
                for name in due:
                    blobs.append(blob)
                    names.append(name)
                    found.append([{"kind": k, "s": s, "e": e} for k, s, e in scanners[name](body)])
            yield pa.RecordBatch.from_arrays([pa.array(blobs, pa.string()), pa.array(names, pa.string()), pa.array(found, kind)], ["blob", "rule", "findings"])

    def pack(batches):
        import pyarrow as pa

        for b in batches:  # what the join moves is compressed first
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([zlib.compress((t.as_py() or "").encode(), 1) for t in b.column(2)], pa.binary())], ["path", "blob", "body"])

    kind = paths.schema[path].dataType.simpleString()
    blob = F.sha2(F.coalesce(F.col(text), F.lit("")).cast("binary"), 256)
    packed = paths.select(F.col(path).alias("path"), blob.alias("blob"), F.col(text).alias("body")).mapInArrow(pack, f"path {kind}, blob string, body binary")
    # a path may hold several texts and may be null: only the row that holds the blob stands for it
    due = pending.select(F.col("path").alias("_path"), F.col("blob").alias("_blob"), "rules")
    todo = packed.join(due, (F.col("blob") == F.col("_blob")) & F.col("path").eqNullSafe(F.col("_path"))).select("body", "blob", "rules")
    return todo.mapInArrow(run, f"blob string, rule string, findings {FINDING}").dropDuplicates(["blob", "rule"])


def report(versions: DataFrame, ledger: DataFrame, rules=None) -> DataFrame:
    """(path, blob, findings): the current rules' findings, at every path that holds the blob."""
    now = [f"{r}@{v}" for r, v, _ in rules or RULES]
    hits = ledger.where(F.col("rule").isin(now) & (F.size("findings") > 0)).groupBy("blob").agg(F.flatten(F.collect_list("findings")).alias("findings"))
    return versions.join(hits, "blob", "left").select("path", "blob", F.coalesce("findings", F.array().cast(FINDING)).alias("findings"))


def update(paths: DataFrame, ledger_path: str, **kw) -> DataFrame:
    """Bring the ledger table at ledger_path up to date with these versions; returns the report."""
    spark = paths.sparkSession
    versions = address(paths, **kw)
    try:
        ledger = spark.read.parquet(ledger_path)
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        ledger = None
    scan(paths, unseen(versions, ledger), **kw).write.mode("append").parquet(ledger_path)
    return report(versions, spark.read.parquet(ledger_path))


def find_secrets(docs: DataFrame) -> DataFrame:
    """doc_id and findings of a first run, with an empty ledger."""
    versions = durable(address(docs))
    return report(versions, durable(scan(docs, unseen(versions, None)))).select(F.col("path").alias("doc_id"), "findings")


def digest(findings) -> "F.Column":
    """kind:start:end by start, then kind as listed."""
    place = lambda k: F.when(k == "assign", 0).when(k == "access", 1).when(k == "hex", 2).otherwise(3)
    rows = F.array_sort(F.transform(findings, lambda x: F.struct(x["s"].alias("s"), place(x["kind"]).alias("p"), x["kind"].alias("kind"), x["e"].alias("e"))))
    return F.array_join(F.transform(rows, lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))), ",")
