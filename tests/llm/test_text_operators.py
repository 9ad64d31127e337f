import hashlib
import re
import struct

import pytest

from flowblocks.llm import bpe_codec, decontaminate, embedding_neardup, language_id, license_scan, line_dedup, ngram_join, pii, secret_scan, token_attribution

DOCS = "doc_id bigint, text string"
ODD = [(1, None), (2, ""), (3, "a"), (4, "x" * 60_000), (5, "same line here\nother"), (6, "same line here"), (7, "same line here"), (7, "same line here")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def test_bpe_equals_the_library(spark):
    P = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    path = P.path("word_bpe_49k.json")
    lib, own = Tokenizer.from_file(path), bpe_codec.WordBpe(path)
    for text in ["", "Hello, World's 42!", "Straße ΣΑΣ İstanbul don't", "<|endoftext|>a<|startoftext|>", "漢字かな交じり文 привет", "a" * 500, "x\u0085y z\x1c.", "é é ﬁ 👍🏽"]:
        ids = lib.encode(text, add_special_tokens=False).ids
        assert own.encode(text) == struct.pack(f"<{len(ids)}I", *ids)
        assert own.decode(own.encode(text)) == lib.decode(ids, skip_special_tokens=False)


def test_long_words_by_heap_equal_the_scan():
    P = pytest.importorskip("public_tokenizers")
    own = bpe_codec.WordBpe(P.path("word_bpe_49k.json"))
    for word in ("aaaaab" * 20, "therein" * 9, "zq" * 40):
        letters = [*word[:-1], word[-1] + "</w>"]
        assert own._scan(list(letters)) == own._heap(list(letters))


def test_lines(spark, odd, none):
    got = {(r.doc_id, r.n_lines, r.n_dropped, r.text) for r in line_dedup.dedup(odd).collect()}
    assert (5, 2, 0, "same line here\nother") in got and (6, 1, 1, "") in got and (1, 0, 0, None) in got
    assert line_dedup.dedup(none).count() == 0
    t = spark.createDataFrame([(i, f"job {i} ended at 10:{i}") for i in range(10, 14)], DOCS)
    assert sum(r.n_dropped for r in line_dedup.dedup(t).collect()) == 3


def test_licenses(spark, odd):
    t = spark.createDataFrame([(1, "Released under the MIT License. cc by; GNU General Public License, version 3."), *ODD[1:3]], DOCS)
    r = {x.doc_id: x for x in license_scan.report(t).collect()}
    assert r[1].n_base == 3 and (r[1].first_word, r[1].last_word) == (3, 7) and r[1].base_labels == "cc-by,gpl,mit" and "gpl-3.0" in r[1].labels
    assert r[2].n_words == 0 and r[2].first_word is None


def test_ledger_scans_only_what_is_new(spark, odd, tmp_path):
    t = spark.createDataFrame([(1, "token = abcdefghijkl1"), (2, "token = abcdefghijkl1"), (3, None)], DOCS)
    at = str(tmp_path / "ledger")
    assert {r.path: len(r.findings) for r in secret_scan.update(t, at).collect()} == {1: 1, 2: 1, 3: 0}
    ledger = spark.read.parquet(at)
    assert secret_scan.unseen(secret_scan.address(t), ledger).count() == 0
    newer = [(r, v + (r == "hex"), f) for r, v, f in secret_scan.RULES]
    assert [r.rules for r in secret_scan.unseen(secret_scan.address(t), ledger, newer).collect()] == [["hex@2"]] * 2


def test_vectors(spark):
    rows = [(1, [1.0, 0.0], 1), (2, [1.0, 0.01], 1), (3, [1.0, 0.0], 2), (4, None, 1), (5, [0.0, 0.0], 1), (6, [float("nan"), 1.0], 1), (7, [1.0, None], 1), (8, [1.0, 0.0], None)]
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embedding_neardup.near_duplicates(spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int")).collect()}
    assert got[1] == (1, 1, True) and got[2] == (1, 1, False) and all(got[i] == (0, i, True) for i in range(3, 9))


def test_language(spark, odd):
    en, de = "the quick brown fox and the dog ", "der schnelle braune fuchs und der hund "
    t = spark.createDataFrame([(i, (en if i % 2 else de) * 3, "en" if i % 2 else "de") for i in range(60)] + [(100, None, "en"), (101, "123 !", "de")], DOCS + ", lang string")
    got = {r.doc_id: r for r in language_id.identify(t).collect()}
    assert all(got[i].lang_pred == ("en" if i % 2 else "de") and 0 <= got[i].score <= 1 for i in range(60))
    assert got[100].lang_pred == got[101].lang_pred == "und"


def test_sections():
    import numpy as np

    per, crossing = token_attribution.attribute([0, 1, 0], np.array([2, 3]), np.array([0, 3]), "start")
    assert per.tolist() == [2, 1] and crossing == 1
    assert token_attribution.attribute([0, 1, 0], np.array([2, 3]), np.array([0, 3]), "end")[0].tolist() == [1, 2]
    assert token_attribution.attribute([0, 1, 0], np.array([2, 3]), np.array([0, 3]), "majority")[0].tolist() == [1, 2]


def test_templates(spark, odd):
    item = "A train leaves the old station with Anna at 60 km each hour and meets Bob after 3 hours on the line"
    again = "note that A train leaves the old station with Clara at 75 km each hour and meets Dora after 9 hours on the line today"
    broken = item.replace("60", "3").replace("after 3", "after 4").replace("Anna", "Bob")
    docs = spark.createDataFrame([(1, item), (2, again), (3, "nothing of the kind is in this text at all, it is clean and long enough"), (4, None)], DOCS)
    bench = spark.createDataFrame([(9, item), (10, None), (11, "")], "item_id bigint, text string")
    got = {r.doc_id: r for r in decontaminate.report(docs, bench).collect()}
    assert set(got) == {1, 2} and got[1].n_exact == got[1].n_windows and got[2].n_exact < got[2].n_windows
    assert decontaminate.report(docs, bench.limit(0)).count() == 0


def test_jaccard_against_all_pairs(spark, odd, none):
    import random

    rng = random.Random(5)
    base = [" ".join(rng.choice("abcdefghij") + rng.choice("klmnop") for _ in range(60)) for _ in range(6)]
    texts = []
    for b in base:
        for _ in range(6):
            w = b.split()
            for _ in range(rng.randint(0, 2)):
                w[rng.randrange(60)] = "new"
            texts.append(" ".join(w))
    data = list(enumerate(texts)) + [(100, None), (101, ""), (102, "one two"), (103, "one  TWO"), (104, "two")]
    sets = {i: ({tuple(w[j : j + 3]) for j in range(len(w) - 2)} if len(w) > 2 else {tuple(w)} if w else set()) for i, w in ((i, (t or "").lower().split()) for i, t in data)}
    root = {i: i for i in sets}
    find = lambda x: x if root[x] == x else find(root[x])
    for a in sets:
        for b in sets:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 90 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.classes(spark.createDataFrame(data, DOCS)).collect()}
    assert got == {i: (len(s), find(i)) for i, s in sets.items()}
    assert ngram_join.classes(none).count() == 0


def test_pii(spark, odd):
    text = "a.b@c.de.f and +1 (605) 555-9305 4078918989542222, ip 10.0.0.1 999.1.1.1 x@y"
    assert [m[1:] for m in pii.emails(text)] == [m.span() for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    model = pii.trained()
    kinds = [(k, text[s:e]) for k, s, e in pii.method_spans(text, model)]
    assert ("phone", "+1 (605) 555-9305") in kinds and ("card", "4078918989542222") in kinds
    r = {x.doc_id: x for x in pii.find_pii(odd).collect()}
    assert r[1].base_sha256 == hashlib.sha256(b"").hexdigest() and r[1].spans == ""


def brute(ids, m, threshold):
    """{id: (links, component)} of all pairs."""
    import numpy as np

    m = m / np.linalg.norm(m, axis=1, keepdims=True)
    a = m @ m.T >= threshold
    np.fill_diagonal(a, False)
    root = list(range(len(ids)))
    while True:
        new = [min([root[i], *(root[j] for j in np.flatnonzero(a[i]))]) for i in range(len(ids))]
        if new == root:
            return {ids[i]: (int(a[i].sum()), ids[root[i]]) for i in range(len(ids))}
        root = new


def nested(seed, groups=12, size=14, cross=0.94, dim=64):
    """Tight sub-groups around centres whose cosines with one another are about `cross`."""
    import numpy as np

    rng = np.random.default_rng(seed)
    unit = lambda x: x / np.linalg.norm(x, axis=-1, keepdims=True)
    centre = np.sqrt(cross) * unit(rng.standard_normal(dim)) + np.sqrt(1 - cross) * unit(rng.standard_normal((groups, dim)))
    return (unit(centre)[:, None] + 0.004 * unit(rng.standard_normal((groups, size, dim)))).reshape(-1, dim)


def test_links_across_tight_groups_equal_brute_force(spark):
    import numpy as np

    m = np.concatenate([nested(1), nested(2)]).astype(np.float32)
    rows = [(i, [float(x) for x in v], 1) for i, v in enumerate(m)]
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_neardup.near_duplicates(spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int")).collect()}
    assert got == brute(range(len(m)), m.astype(float), embedding_neardup.THRESHOLD)


def test_each_version_of_a_path_is_scanned_under_its_own_blob(spark, tmp_path):
    secret = "token = abcdefghijkl1"
    data = [(i, t) for i in range(20) for t in (secret + f" of {i}", f"nothing to see in {i}")] + [(None, "password: mnopqrstuvwx2")]
    t = spark.createDataFrame(data, DOCS)
    got = [(r.path, len(r.findings)) for r in secret_scan.update(t, str(tmp_path / "ledger")).collect()]
    assert sorted(got, key=str) == sorted([(i, n) for i in range(20) for n in (0, 1)] + [(None, 1)], key=str)
    assert sorted(len(r.findings) for r in secret_scan.find_secrets(t).collect()) == [0] * 20 + [1] * 21


def test_a_long_region_is_decoded_whole():
    model = pii.trained()
    one = "(605) 555-1000"
    assert ("phone", 2, 2 + len(one)) in pii.method_spans("7 " + one, model)
    text = "7 " + " ".join(f"(605) 555-{1000 + i}" for i in range(150))
    (m,) = pii.REGION.finditer(text)
    assert len(pii.atoms_of(text, *m.span())) > 800
    assert [x for x in pii.method_spans(text, model)] == [("phone", 2 + 15 * i, 16 + 15 * i) for i in range(150)]


def test_every_item_can_be_met(spark):
    few = "Compute 3.5 + 4.25 - 1,250 / 7 and then round to 2 places."
    named = "Anna buys some red apples and eats 3 of them at noon"
    two = "The train leaves the station with much noise today. Bob waits there still"
    items = [(1, few), (2, "What is love?"), (3, named), (4, two), (5, ""), (6, "12 + 30")]
    docs = [
        (1, f"so it says: {few} Fine."), (2, "he asked what is love and left"), (3, named.replace("Anna", "Clara")), (4, "we say " + named.replace("Anna", "Dora") + " too"),
        (5, two.replace("The train", "he says the train").replace("Bob", "Carl")), (6, few.replace("1,250", "1,350")), (7, "what was love"), (8, "sum of 12 + 30 is"), (9, None), (10, ""),
    ]
    got = {(r.doc_id, r.item_id): (r.n_windows, r.n_exact) for r in decontaminate.match(spark.createDataFrame(docs, DOCS), spark.createDataFrame(items, "item_id bigint, text string")).collect()}
    assert got == {(1, 1): (1, 1), (2, 2): (1, 1), (3, 3): (1, 0), (4, 3): (1, 0), (5, 4): (1, 0), (8, 6): (1, 1)}


def test_audit_counts_planted_links(spark):
    import numpy as np

    rng = np.random.default_rng(3)
    unit = lambda x: x / np.linalg.norm(x, axis=-1, keepdims=True)
    a = unit(rng.standard_normal((300, 64)))
    b = 0.94 * a + np.sqrt(1 - 0.94**2) * unit(rng.standard_normal((300, 64)))
    m = np.concatenate([a, b, a[:20], nested(4, groups=4)]).astype(np.float32)
    t = spark.createDataFrame([(i, [float(x) for x in v], 1) for i, v in enumerate(m)], "vec_id bigint, embedding array<float>, label int")
    truth = sum(n for n, _ in brute(range(len(m)), m.astype(float), embedding_neardup.THRESHOLD).values())
    assert embedding_neardup.audit_recall(t, embedding_neardup.near_duplicates(t)) == (truth, truth)


def test_long_lines_recur_in_two_documents(spark):
    import corpus_pipeline

    long, short = " ".join(f"word{'abcdefghij'[i // 10]}{'abcdefghij'[i % 10]}" for i in range(50)), "a short line"
    t = spark.createDataFrame([(1, f"one\n{long}\n{short}"), (2, f"two\n{long}\n{short}"), (3, "three"), (4, None)], DOCS).selectExpr("*", "0L n_chars")
    assert {r.doc_id: r.text for r in corpus_pipeline.lines(spark, t, "").collect()} == {1: f"one\n{long}\n{short}", 2: f"two\n{short}", 3: "three", 4: None}
    assert sum(r.n_dropped for r in line_dedup.report(t).collect()) == 0
