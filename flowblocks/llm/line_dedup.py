"""Line dedup (operator 1), DataFrame functions only: a log-template tree over the lines of all documents.

A token with a digit is a field, `<*>`. A line's path in the tree is its token count, then its first DEPTH tokens; a
leading token that fewer than min_docs documents have under its node is a field there too. A leaf of two lines or more
and at least LITERAL literal leading tokens, standing in min_docs documents or more, generalises: at each later place it keeps the
token of more than half of its documents (a document counts once for each different line) and has a field elsewhere. A
line of MIN_TOKENS tokens or more that agrees with SIMILAR percent of those later places takes the leaf's template;
every other line is a template of its own.

A template that occurs in min_docs documents or more is recurring: its lines are dropped from every document but the one
with the smallest doc_id, where they stay as they are. Blank lines are neither counted nor dropped. Null text stays null;
rows of one doc_id are one document, equal or not; rows with a null doc_id keep all their lines and count for no template; a very
long line or text is one row of hashes; other columns pass through, whatever their names, but n_lines and n_dropped,
which are replaced; an empty table gives an empty table.
"""
from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, bitmap, marked

DEPTH, MIN_DOCS, MIN_TOKENS, LITERAL, SIMILAR = 3, 3, 8, 2, 60
#: Words from which a line recurs in two documents already, where a caller asks for it.
LONG = 50
FIELD = r"(?<![^ \n])[^ \n0-9]*+[0-9][^ \n]*+"
BLANKS = ("\t", "\r", "\f", "\x0b", "  ", " \n", "\n ")
LEADING = ["a", "b", "c"]


def flattened(text: Column) -> Column:
    """The whole text with runs of blanks made one and line ends bare; line breaks stay in place."""
    odd = F.contains(text, F.lit(BLANKS[0]))
    for x in BLANKS[1:]:
        odd = odd | F.contains(text, F.lit(x))
    flat = F.when(odd, F.regexp_replace(F.regexp_replace(text, r"[\t\r\f\x0B ]+", " "), r"(?<=\n) | (?=\n)", "")).otherwise(text)
    return F.trim(flat)


def split_lines(flat: Column) -> Column:
    """Lines of a flattened text, tokens with a digit as `<*>`. It reads its argument twice, so that is to be a column."""
    return F.split(F.when(flat.rlike("[0-9]"), F.regexp_replace(flat, FIELD, "<*>")).otherwise(flat), "\n", -1)


def key(line: Column) -> Column:
    return F.xxhash64(F.lit(1), line)


def lines_of(docs: DataFrame) -> DataFrame:
    """doc_id, row (the text's hash), at, line (its hash, null where blank), n (tokens), and of lines that may generalise
    a, b, c (hashes of the leading tokens) and body."""
    rows = docs.where("text is not null and doc_id is not null").select("doc_id", F.xxhash64("text").alias("row"), flattened(F.col("text")).alias("flat"))
    rows = rows.select("doc_id", "row", F.posexplode(split_lines(F.col("flat"))).alias("at", "t"))
    rows = rows.withColumn("n", F.when(F.col("t") != "", F.length("t") - F.length(F.replace("t", F.lit(" "), F.lit(""))) + 1))
    long, lead = F.col("n") >= MIN_TOKENS, F.split("t", " ", DEPTH + 1)
    return rows.select("doc_id", "row", "at", F.when(F.col("n").isNotNull(), key(F.col("t"))).alias("line"), "n", *[F.when(long, F.xxhash64(lead[i])).alias(c) for i, c in enumerate(LEADING)], F.when(long, F.col("t")).alias("body"))


def leaves(lines: DataFrame, min_docs: int) -> DataFrame:
    """line, first, n, k, leaf, lk (documents of the leaf) of the lines in leaves that generalise; lines is one row for each line."""
    rows, path, literal = lines.where(F.col("n") >= MIN_TOKENS), ["n"], F.lit(0)
    field = F.lit(0).cast("bigint")
    for left, c in zip((2, 1, 0), LEADING):
        node = rows.groupBy(*path, c).agg(F.sum("k").alias("under")).where(F.col("under") >= min_docs)
        rows = rows.join(node.hint("merge"), [*path, c], "left").withColumn(f"p_{c}", F.when(F.col("under").isNotNull(), F.col(c)).otherwise(field)).withColumn(f"l_{c}", F.col("under").isNotNull().cast("int")).drop("under", c)
        path, literal = [*path, f"p_{c}"], literal + F.col(f"l_{c}")
        rows = rows.where(literal + left >= LITERAL)  # whole nodes go, so the counts below stay
    rows = rows.select("line", "first", "n", "k", F.xxhash64(F.lit(2), *path).alias("leaf"))
    size = rows.groupBy("leaf").agg(F.sum("k").alias("lk"), F.count("*").alias("lines")).where((F.col("lk") >= min_docs) & (F.col("lines") > 1)).drop("lines")
    return rows.join(size, "leaf")


def members(docs: DataFrame, cand: DataFrame, disk: Scratch) -> DataFrame:
    """line, leaf of the lines that agree with the template of their leaf. Their tokens are read from the first document of each
    once more; a bitmap of these documents goes to all, so no table holds the texts of lines."""
    of = docs.select("doc_id", "text").join(F.broadcast(bitmap(cand.select(F.xxhash64("first")))), F.lit(True)).where(marked(F.col("bits"), F.xxhash64("doc_id"))).select("doc_id", "text")
    held = lines_of(of).where("body is not null").join(F.broadcast(bitmap(cand.select("line"))), F.lit(True)).where(marked(F.col("bits"), F.col("line")))
    held = held.select(F.col("doc_id").alias("first"), "line", "body").join(cand.hint("merge"), ["first", "line"]).dropDuplicates(["line"])
    tokens = F.split("body", " ", -1)
    later = F.transform(F.slice(tokens, DEPTH + 1, F.size(tokens)), lambda x, i: F.xxhash64(i, x))
    own = disk.keep("members", held.select("line", "leaf", "n", "k", "lk", later.alias("later")))
    votes = own.select("leaf", "lk", "k", F.explode("later").alias("v")).groupBy("leaf", "lk", "v").agg(F.sum("k").alias("w")).where(F.col("w") * 2 > F.col("lk"))
    template = votes.groupBy("leaf").agg(F.collect_list("v").alias("kept"))
    agree = F.size(F.array_intersect("later", "kept")) * 100 >= (F.col("n") - DEPTH) * SIMILAR
    return own.join(template, "leaf").where(agree).select("line", "leaf")


def marks(docs: DataFrame, disk: Scratch, min_docs: int = MIN_DOCS, long_words: int | None = None) -> DataFrame:
    """doc_id, row, gone (one mark for each line, in order) of every text that loses a line."""
    each = disk.keep("each", lines_of(docs).drop("body"))
    once = each.where("line is not null").select("doc_id", "line", "n", *LEADING).distinct()
    lines = disk.keep("lines", once.groupBy("line").agg(F.count("*").alias("k"), F.min("doc_id").alias("first"), *[F.first(c).alias(c) for c in ("n", *LEADING)]))
    disk.drop()
    cand = disk.keep("cand", leaves(lines, min_docs))
    disk.drop()
    like = disk.keep("like", members(docs, cand, disk))
    disk.drop("cand", "members")
    of_leaf = each.select("doc_id", "line").join(like, "line").select("leaf", "doc_id").distinct().groupBy("leaf").agg(F.count("*").alias("k"), F.min("doc_id").alias("first")).where(F.col("k") >= min_docs).drop("k")
    enough = F.col("k") >= (F.when(F.col("n") >= long_words, min(2, min_docs)).otherwise(min_docs) if long_words else min_docs)
    recurring = disk.keep("recurring", lines.where(enough).select("line", "first").join(like, "line", "left_anti").union(like.join(of_leaf, "leaf").select("line", "first")))
    disk.drop("lines", "like")
    drop = disk.keep("drop", each.select("doc_id", "line").join(recurring, "line").where("doc_id <> first").select("doc_id", "line").distinct())
    disk.drop("recurring")
    # only texts that lose a line are put together again
    hit = each.select("doc_id", "row", "at", "line").join(drop.select("doc_id").distinct(), "doc_id", "left_semi").join(drop.withColumn("gone", F.lit(True)), ["doc_id", "line"], "left")
    gone = hit.groupBy("doc_id", "row").agg(F.array_sort(F.collect_set(F.struct("at", F.coalesce("gone", F.lit(False)).alias("gone")))).alias("gone"))
    out = disk.keep("marks", gone.select("doc_id", "row", F.transform("gone", lambda m: m["gone"]).alias("gone")))
    disk.drop("each", "drop")
    return out


def dedup(docs: DataFrame, min_docs: int = MIN_DOCS, long_words: int | None = None) -> DataFrame:
    """docs with text less the dropped lines, plus n_lines and n_dropped (bigint); with long_words, lines of so many words
    recur from two documents on."""
    own = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    docs = docs.select(own)
    mark = marks(docs, Scratch(docs.sparkSession), min_docs, long_words).select(F.struct("doc_id", "row", "gone").alias("mark"))
    both = docs.select(F.struct(*own).alias("doc")).join(mark.hint("merge"), (F.col("doc.doc_id") == F.col("mark.doc_id")) & (F.xxhash64("doc.text") == F.col("mark.row")), "left")
    text, gone = F.col("doc.text"), F.col("mark.gone")
    kept = F.transform(F.filter(F.zip_with(F.split(text, "\n", -1), gone, lambda x, g: F.struct(x.alias("x"), g.alias("g"))), lambda m: ~m["g"]), lambda m: m["x"])
    n_lines = F.coalesce((F.length(text) - F.length(F.replace(text, F.lit("\n"), F.lit(""))) + 1).cast("bigint"), F.lit(0))
    n_dropped = F.coalesce(F.size(F.filter(gone, lambda g: g)), F.lit(0)).cast("bigint")
    new = F.when(gone.isNotNull(), F.array_join(kept, "\n")).otherwise(text)
    return both.select(*[(new if c == "text" else F.col("doc").getField(c)).alias(c) for c in own], n_lines.alias("n_lines"), F.when(gone.isNull(), 0).otherwise(n_dropped).cast("bigint").alias("n_dropped"))


def report(docs: DataFrame) -> DataFrame:
    return dedup(docs.select("doc_id", "text")).select("doc_id", "n_lines", "n_dropped", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("kept_md5"))


#: The same over DuckDB tables; hashes of the tree's nodes are the tokens themselves there.
CLEAN_SQL = r"""case when regexp_matches(line, '[\t\r\f\v]|  ') then trim(regexp_replace(line, '[\t\r\f\v ]+', ' ', 'g'), ' ') else trim(line, ' ') end"""
_NODE = "case when sum(k) over (partition by {path}, {c}) >= {m} then {c} else '' end"
SQL = rf"""
with lines as (
  select doc_id, text, unnest(string_split(text, chr(10))) line, generate_subscripts(string_split(text, chr(10)), 1) i from documents where text is not null),
flat as (select doc_id, i, line, {CLEAN_SQL} f from lines),
t as (select doc_id, i, line, array_to_string(list_transform(string_split(f, ' '), lambda x: case when regexp_matches(x, '[0-9]') then '<*>' else x end), ' ') tpl from flat),
l as (select tpl, count(distinct doc_id) k, min(doc_id) first_doc, string_split(tpl, ' ') w, len(string_split(tpl, ' ')) n from t where tpl <> '' group by tpl),
t1 as (select *, {_NODE.format(path="n", c="w[1]", m=MIN_DOCS)} p1 from l where n >= {MIN_TOKENS}),
t2 as (select *, {_NODE.format(path="n, p1", c="w[2]", m=MIN_DOCS)} p2 from t1),
t3 as (select *, {_NODE.format(path="n, p1, p2", c="w[3]", m=MIN_DOCS)} p3 from t2),
leaf as (select *, sum(k) over (partition by n, p1, p2, p3) lk, count(*) over (partition by n, p1, p2, p3) lines from t3
  where (p1 <> '')::int + (p2 <> '')::int + (p3 <> '')::int >= {LITERAL} qualify lk >= {MIN_DOCS} and lines > 1),
later as (select n, p1, p2, p3, lk, k, tpl, unnest(w[{DEPTH + 1}:]) v, generate_subscripts(w[{DEPTH + 1}:], 1) p from leaf),
kept as (select n, p1, p2, p3, p, v from later group by n, p1, p2, p3, lk, p, v having sum(k) * 2 > lk),
own as (select tpl, n, p1, p2, p3 from later semi join kept using (n, p1, p2, p3, p, v) group by tpl, n, p1, p2, p3 having count(*) * 100 >= (n - {DEPTH}) * {SIMILAR}),
rec_leaf as (select n, p1, p2, p3, min(doc_id) first_doc from t join own using (tpl) group by n, p1, p2, p3 having count(distinct doc_id) >= {MIN_DOCS}),
rec as (select tpl, first_doc from l anti join own using (tpl) where k >= {MIN_DOCS} union all select tpl, first_doc from own join rec_leaf using (n, p1, p2, p3)),
m as (select t.*, (rec.tpl is not null and t.doc_id <> rec.first_doc) gone from t left join rec using (tpl)),
s as (select doc_id, count(*) n_lines, count(*) filter (where gone) n_dropped, coalesce(string_agg(line, chr(10) order by i) filter (where not gone), '') kept from m group by doc_id)
select d.doc_id, coalesce(n_lines, 0)::bigint n_lines, coalesce(n_dropped, 0)::bigint n_dropped, md5(coalesce(kept, '')) kept_md5 from documents d left join s using (doc_id)
"""
