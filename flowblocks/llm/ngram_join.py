"""N-gram Jaccard join (operator 9) through a token-group matrix; exact up to 64-bit hashing of shingles.

Equal sets collapse first. A token order that puts corpus-wide rare tokens first comes from a table of fixed size that
covers every document; it decides how much is compared, never what links. Each set posts the rare end of its tokens, with
how many of its tokens lie from there on: two sets that link share a posted token, and the first one they share leaves
enough tokens on both sides. Similar sets are partitioned into groups (star links to the first set under a key of smallest
hashes, verified; they only save comparisons, the matrix finds what they miss); the matrix holds the union of a group's posted tokens, an entry for each. A query set meets a group through an
entry that leaves enough tokens. Parities of all its tokens, in bins, differ from those that the members have in common in no
more bins than it differs from a member in tokens, so most meetings end there, before tokens are counted (larger sets have
more bins, so that they do not fill up); the tokens it
shares with the union bound its overlap with every member, and only groups whose bound can reach the threshold are
opened, member by member, by parities again. What is left is compared token by token.

Texts that are null or empty have no shingle and link with nothing; a null doc_id has a null component; equal rows count
once, and a doc_id with several texts links where any of them does; ties keep the smallest doc_id; one very long text is
one large set; other columns are not read; an empty table gives an empty table.
"""
from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, bitmap, components, marked
from .word_stream import mix, windows, words

FREQ_BITS, CHUNKS = 18, 64
#: Keys of a set, and smallest hashes in each of them.
BANDS, WIDE = 8, 8
#: Words of 64 parities of a set. A set of more tokens than parities has STEP times as many on a finer level, and so on.
PARITY, STEP = 8, 4


def shingles(text: str | None, n: int = 3) -> np.ndarray:
    """Sorted distinct shingle hashes; a shorter text is one shingle."""
    h = words((text or "").encode())[0]
    if not len(h):
        return h
    return np.unique(windows(h, n) if len(h) >= n else windows(h, len(h)))


def lead(n: int, num: int, den: int) -> int:
    """How many of n tokens, rarest first, meet any set that links: n - ceil(t n) + 1."""
    return n - -(-num * n // den) + 1 if n else 0


def frequencies(docs: DataFrame, n: int) -> np.ndarray:
    """Tokens by hash bucket over all documents; the table's size is fixed at 2^FREQ_BITS. Tasks send theirs in CHUNKS pieces."""
    width = (1 << FREQ_BITS) // CHUNKS

    def count(batches):
        import pyarrow as pa

        total = np.zeros(1 << FREQ_BITS, np.int64)
        for b in batches:
            for text in b.column(0):
                np.add.at(total, (shingles(text.as_py(), n) >> np.uint64(64 - FREQ_BITS)).astype(np.int64), 1)
        yield pa.RecordBatch.from_arrays([pa.array(range(CHUNKS), pa.int32()), pa.array([x.tobytes() for x in total.reshape(CHUNKS, width)], pa.binary())], ["chunk", "part"])

    def add(t):
        import pyarrow as pa

        total = np.zeros(width, np.int64)
        for x in t.column("part"):
            total += np.frombuffer(x.as_py(), np.int64)
        return pa.table({"chunk": pa.array([t.column("chunk")[0].as_py()], pa.int32()), "part": pa.array([total.tobytes()], pa.binary())})

    out = np.zeros((CHUNKS, width), np.int64)
    for r in docs.select("text").mapInArrow(count, "chunk int, part binary").groupBy("chunk").applyInArrow(add, "chunk int, part binary").collect():
        out[r.chunk] = np.frombuffer(r.part, np.int64)
    return out.ravel()


def signatures(docs: DataFrame, n: int, num: int, den: int) -> DataFrame:
    """doc_id, size, digest (a, b) of the set, its posted tokens, rarest first, its keys and parities, of every document."""
    rare = docs.sparkSession.sparkContext.broadcast(frequencies(docs, n))

    def run(batches):
        import pyarrow as pa

        freq = rare.value
        for batch in batches:
            size, a, b, posts, keys, parities, more = [], [], [], [], [], [], []
            for text in batch.column(1):
                h = shingles(text.as_py(), n)
                size.append(len(h))
                x, y = digest(h)
                a.append(x)
                b.append(y)
                first = np.lexsort((h, freq[(h >> np.uint64(64 - FREQ_BITS)).astype(np.int64)]))[: lead(len(h), num, den)]
                posts.append(h[first].view(np.int64))
                keys.append(bands(h))
                parities.append(parity(h))
                more.append(finer(h))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size, pa.int32()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), listed(posts), listed(keys), listed(parities), listed(more)], ["doc_id", "n", "a", "b", "posts", "keys", "parity", "finer"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n int, a bigint, b bigint, posts array<bigint>, keys array<bigint>, parity array<bigint>, finer array<bigint>")


def digest(h: np.ndarray) -> tuple[int, int]:
    """Two sums over a set's hashes that no order changes."""
    if not len(h):
        return 0, 0
    with np.errstate(over="ignore"):
        return int(h.sum(dtype=np.uint64).view(np.int64)), int(mix(h ^ np.uint64(0xA5A5A5A5A5A5A5A5)).sum(dtype=np.uint64).view(np.int64))


def bands(h: np.ndarray) -> np.ndarray:
    """Keys that similar sets tend to share: the range of hashes falls into BANDS * WIDE equal parts, and a key is made of the
    smallest hash in each of WIDE parts. A key whose parts are all empty is left out."""
    at = np.searchsorted(h, np.arange(BANDS * WIDE, dtype=np.uint64) << np.uint64(64 - (BANDS * WIDE).bit_length() + 1))
    held = np.append(at[1:], len(h)) > at
    first = np.zeros(BANDS * WIDE, np.uint64)
    first[held] = h[at[held]]
    with np.errstate(over="ignore"):
        keys = mix(first + np.arange(BANDS * WIDE, dtype=np.uint64)).reshape(BANDS, WIDE).sum(axis=1, dtype=np.uint64)
    return keys[held.reshape(BANDS, WIDE).any(axis=1)].view(np.int64)


def parity(h: np.ndarray) -> np.ndarray:
    """Whether the number of tokens in each of 64 * PARITY bins is odd: sets that differ in k tokens differ in k bins at most."""
    bins = np.bincount((h & np.uint64(64 * PARITY - 1)).astype(np.int64), minlength=64 * PARITY)
    return np.packbits((bins & 1).astype(np.uint8)).view(np.int64)


def finer(h: np.ndarray) -> np.ndarray:
    """Parities of a set in more bins, level after level, until there is a bin for each token; none for a set that `parity` suits."""
    out, n = [np.zeros(0, np.int64)], 64 * PARITY
    while n < len(h):
        n *= STEP
        out.append(np.packbits((np.bincount((h & np.uint64(n - 1)).astype(np.int64), minlength=n) & 1).astype(np.uint8)).view(np.int64))
    return np.concatenate(out)


def listed(arrays):
    import pyarrow as pa

    ends = np.cumsum([0, *map(len, arrays)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(arrays) if arrays else np.zeros(0, np.int64)))


def full_sets(docs: DataFrame, n: int) -> DataFrame:
    def run(batches):
        import pyarrow as pa

        for batch in batches:
            sets = [shingles(t.as_py(), n).view(np.int64) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), listed(sets)], ["rid", "tokens"])

    return docs.select(F.col("doc_id").alias("rid"), "text").mapInArrow(run, "rid bigint, tokens array<bigint>")


def near_sizes(a, b, num: int, den: int):
    return (F.col(a) * num <= F.col(b) * den) & (F.col(b) * num <= F.col(a) * den)


def enough(shared, size_u, size_v, num: int, den: int):
    """Whether so many shared tokens could make sets of these sizes link."""
    return shared * (num + den) >= (F.col(size_u) + size_v) * num


def apart(one: str, all_: str, any_: str):
    """The least number of bins in which a set's parities differ from those of any set of a group, by the bins that are odd in
    all and in any of them."""
    out = F.lit(0)
    for i in range(PARITY):
        x = F.get(one, F.lit(i))
        out = out + F.bit_count(x.bitwiseAND(F.bitwise_not(F.get(any_, F.lit(i))))) + F.bit_count(F.bitwise_not(x).bitwiseAND(F.get(all_, F.lit(i))))
    return out


def finest_apart(one: str, all_: str, any_: str):
    """As `apart`, by the finest level of `finer` that both sides have; 0 where there is none."""
    end = F.least(F.size(one), F.size(all_))
    start = F.greatest(F.floor((end - PARITY * STEP) / STEP).cast("int"), F.lit(0))
    bins = F.transform(F.slice(one, start + 1, end - start), lambda x, i: F.bit_count(x.bitwiseAND(F.bitwise_not(F.get(any_, start + i)))) + F.bit_count(F.bitwise_not(x).bitwiseAND(F.get(all_, start + i))))
    return F.aggregate(bins, F.lit(0), lambda a, b: a + b)


def few(bins, size_u, size_v, num: int, den: int):
    """Whether sets of these sizes that differ in so many tokens at least could link."""
    return bins * (num + den) <= (F.col(size_u) + size_v) * (den - num)


def close(pairs: DataFrame, prints: DataFrame, num: int, den: int) -> DataFrame:
    """Those of the pairs (u, v) that parities do not rule out; prints is (rid, size, parity)."""
    of = lambda c: prints.select(F.col("rid").alias(c), F.col("size").alias(f"s{c}"), F.col("parity").alias(f"p{c}")).hint("merge")
    return pairs.join(of("u"), "u").join(of("v"), "v").where(few(apart("pu", "pv", "pv"), "su", F.col("sv"), num, den)).select("u", "v").distinct()


def verify(disk: Scratch, name: str, pairs: DataFrame, docs: DataFrame, n: int, num: int, den: int) -> DataFrame:
    """Those of the pairs (u, v) that link. Only the sets of their documents are made again and moved, never a text: a bitmap of
    their ids, of fixed size, goes to all documents."""
    ids = disk.keep(f"{name}-ids", pairs.select(F.col("u").alias("rid")).union(pairs.select(F.col("v").alias("rid"))).distinct())
    of = docs.join(F.broadcast(bitmap(ids.select(F.xxhash64("rid")))), F.lit(True)).where(marked(F.col("bits"), F.xxhash64("doc_id")))
    sets = disk.keep(f"{name}-sets", full_sets(of, n).join(ids.hint("merge"), "rid", "left_semi"))
    both = pairs.join(sets.select(F.col("rid").alias("u"), F.col("tokens").alias("tu")).hint("merge"), "u").join(sets.select(F.col("rid").alias("v"), F.col("tokens").alias("tv")).hint("merge"), "v")
    both = both.withColumn("i", F.size(F.array_intersect("tu", "tv")))
    out = disk.keep(name, both.where(F.col("i") * den >= (F.size("tu") + F.size("tv") - F.col("i")) * num).select("u", "v").distinct())
    disk.drop(f"{name}-sets", f"{name}-ids")  # and the shuffles of its two joins
    return out


def alike_pairs(keyed: DataFrame, num: int, den: int) -> DataFrame:
    """Each set with one set under each of its keys, (u, v), where sizes allow a link; keyed is (key, rid, size). Every key has
    its own order of sets, so a group does not hang on one of them."""
    hubs = keyed.groupBy("key").agg(F.min(F.struct(F.xxhash64("key", "rid").alias("place"), "rid", "size")).alias("hub"), F.count("*").alias("k")).where("k > 1").drop("k")
    pairs = keyed.join(hubs.hint("merge"), "key").select(F.col("rid").alias("u"), F.col("hub.rid").alias("v"), "size", F.col("hub.size").alias("hub_size"))
    return pairs.where((F.col("u") != F.col("v")) & near_sizes("size", "hub_size", num, den)).select("u", "v").distinct()


def among(meet: DataFrame, column: str):
    """A filter of tables to rows whose id may be in a column of meet, by a bitmap of fixed size."""
    bits = F.broadcast(bitmap(meet.select(F.xxhash64(column))))
    return lambda rows, id_: rows.join(bits, F.lit(True)).where(marked(F.col("bits"), F.xxhash64(id_))).drop("bits")


def still_near(meet: DataFrame, cards: DataFrame, num: int, den: int) -> DataFrame:
    """Those of the meetings (u, su, g) that finer parities do not rule out; cards is (rid, g, size, parity, finer). A group has the
    levels that all its members have."""
    of_group = among(meet, "g")(cards.select("g", "size", "finer"), "g")
    words = of_group.select("g", F.posexplode("finer").alias("pos", "w")).groupBy("g", "pos").agg(F.bit_and("w").alias("all"), F.bit_or("w").alias("any"))
    words = words.groupBy("g").agg(F.array_sort(F.collect_list(F.struct("pos", "all", "any"))).alias("w"))
    held = of_group.groupBy("g").agg(F.max("size").alias("hi"), F.min(F.size("finer")).alias("k")).join(words.hint("merge"), "g", "left")
    common = held.select("g", "hi", *(F.coalesce(F.slice(f"w.{c}", 1, F.col("k")), F.array().cast("array<bigint>")).alias(c) for c in ("all", "any")))
    mine = among(meet, "u")(cards.select(F.col("rid").alias("u"), F.col("size").alias("su"), F.col("finer").alias("fu")), "u")
    most = F.least(F.col("hi"), F.floor(F.col("su") * den / num))
    near = meet.join(mine.hint("merge"), ["u", "su"]).join(common.hint("merge"), "g").where(few(finest_apart("fu", "all", "any"), "su", most, num, den))
    return near.select("u", "su", "g").distinct()


def candidates(disk: Scratch, shared: DataFrame, group: DataFrame, prints: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs (u, v) of different groups that matrix and parities cannot rule out; shared is (tok, rid, size, rest), group (rid, g),
    prints (rid, size, parity, finer)."""
    placed = disk.keep("placed", shared.join(group, "rid", "left").select("tok", "rid", "size", "rest", F.coalesce("g", "rid").alias("g")))
    # one entry of the matrix: a token in the union of a group, with the sizes of the sets that post it and the most of any of them that lies from it on
    entry = placed.groupBy("tok", "g").agg(F.min("size").alias("lo"), F.max("size").alias("hi"), F.max("rest").alias("most"))
    met = entry.groupBy("tok").agg(F.count("*").alias("k")).where("k > 1").drop("k")
    matrix = disk.keep("matrix", entry.join(met.hint("merge"), "tok"))
    least = lambda size: F.ceil(F.col(size) * num / den)
    query = placed.select("tok", F.col("rid").alias("u"), F.col("g").alias("gu"), F.col("size").alias("su"), "rest")
    fits = (F.col("g") < F.col("gu")) & (F.col("lo") * num <= F.col("su") * den) & (F.col("su") * num <= F.col("hi") * den)
    meet = query.join(matrix.hint("merge"), "tok").where(fits & enough(F.least("rest", "most"), "su", F.greatest("lo", least("su")), num, den))
    meet = disk.keep("meet", meet.select("u", "su", "g").distinct())
    # parities of the queries and of what the groups' members have in common
    ids = F.broadcast(bitmap(meet.select(F.xxhash64("u")).union(meet.select(F.xxhash64("g")))))
    cards = prints.join(group, "rid", "left").withColumn("g", F.coalesce("g", "rid")).join(ids, F.lit(True)).where(marked(F.col("bits"), F.xxhash64("rid")) | marked(F.col("bits"), F.xxhash64("g")))
    cards = disk.keep("cards", cards.select("rid", "g", "size", "parity", "finer"))
    words = lambda f: F.array(*[f(F.get("parity", F.lit(i))) for i in range(PARITY)])
    common = cards.groupBy("g").agg(words(F.bit_and).alias("all"), words(F.bit_or).alias("any"), F.max("size").alias("hi"))
    mine = cards.select(F.col("rid").alias("u"), F.col("size").alias("su"), F.col("parity").alias("pu"))
    most = F.least(F.col("hi"), F.floor(F.col("su") * den / num))
    alike = meet.join(mine.hint("merge"), ["u", "su"]).join(common.hint("merge"), "g").where(few(apart("pu", "all", "any"), "su", most, num, den))
    meet = disk.keep("near", alike.select("u", "su", "g").distinct())
    meet = disk.keep("nearer", still_near(meet, cards, num, den))
    # a query's overlap with a group's union bounds its overlap with every member: posted tokens met, and at most what lies behind the longer prefix
    of_group = placed.groupBy("g").agg(F.min("size").alias("lo"), F.max("size").alias("hi"))
    asking, asked = among(meet, "u"), among(meet, "g")
    met_u = meet.hint("merge").join(asking(placed, "rid").select(F.col("rid").alias("u"), "tok").distinct(), "u")
    overlap = met_u.join(asked(matrix.select("tok", "g"), "g").hint("merge"), ["tok", "g"]).groupBy("u", "su", "g").agg(F.count("*").alias("c"))
    behind = F.greatest(least("su"), F.ceil(F.least(F.col("hi"), F.floor(F.col("su") * den / num)) * num / den)) - 1
    opened = overlap.join(of_group, "g").where(enough(F.col("c") + behind, "su", F.greatest("lo", least("su")), num, den)).select("u", "su", "g")
    opened = disk.keep("opened", opened)
    them = asked(cards, "g").select("g", F.col("rid").alias("v"), F.col("size").alias("sv"), F.col("parity").alias("pv"), F.col("finer").alias("fv"))
    us = asking(cards, "rid").select(F.col("rid").alias("u"), F.col("size").alias("su"), F.col("parity").alias("pu"), F.col("finer").alias("fu"))
    can = near_sizes("su", "sv", num, den) & few(apart("pu", "pv", "pv"), "su", F.col("sv"), num, den) & few(finest_apart("fu", "fv", "fv"), "su", F.col("sv"), num, den)
    pairs = opened.hint("merge").join(us, ["u", "su"]).join(them.hint("merge"), "g").where(can)
    out = disk.keep("pairs", pairs.select("u", "v").distinct())
    disk.drop("placed", "matrix", "meet", "cards", "near", "nearer", "opened")
    return out


def classes(docs: DataFrame, n: int = 3, num: int = 90, den: int = 100) -> DataFrame:
    """doc_id, n_shingles, component_id of the link relation num/den over n-word shingles."""
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    disk = Scratch(docs.sparkSession)
    sig = disk.keep("signatures", signatures(docs, n, num, den))
    whole = sig.select("doc_id", "n", "a", "b")
    alike = whole.where("n > 0 and doc_id is not null").groupBy("a", "b", "n").agg(F.count("*").alias("k"), F.min("doc_id").alias("rid")).where("k > 1")
    alike = disk.keep("alike", alike.drop("k"))
    own = sig.where("n > 0 and doc_id is not null").join(alike, ["a", "b", "n"], "left").where("rid is null or rid = doc_id")
    posts = own.select(F.col("doc_id").alias("rid"), F.col("n").alias("size"), F.posexplode("posts").alias("at", "tok")).select("tok", "rid", "size", (F.col("size") - F.col("at")).alias("rest"))
    met = disk.keep("met", posts.groupBy("tok").agg(F.count("*").alias("k")).where("k > 1").drop("k"))
    disk.drop()
    shared = disk.keep("shared", posts.join(met.hint("merge"), "tok"))  # the same way at every size
    disk.drop("met")
    keyed = own.select(F.explode("keys").alias("key"), F.col("doc_id").alias("rid"), F.col("n").alias("size"))
    prints = sig.where("n > 0 and doc_id is not null").select(F.col("doc_id").alias("rid"), F.col("n").alias("size"), "parity", "finer")
    stars = disk.keep("stars", alike_pairs(keyed, num, den))
    sure = verify(disk, "sure", disk.keep("close", close(stars, prints, num, den)), docs, n, num, den)
    disk.drop("stars", "close")
    group = components(sure).select(F.col("id").alias("rid"), F.col("component").alias("g"))
    late = verify(disk, "late", candidates(disk, shared, group, prints, num, den), docs, n, num, den)
    disk.drop("shared", "pairs")
    linked = components(sure.union(late)).select(F.col("id").alias("rid"), "component")
    out = disk.keep("rows", whole.join(alike, ["a", "b", "n"], "left").select("doc_id", F.col("n").cast("bigint").alias("n_shingles"), F.coalesce("rid", "doc_id").alias("rid")).join(linked, "rid", "left").select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "rid")).alias("component_id")))
    disk.drop("signatures", "alike", "sure", "late")
    return out
