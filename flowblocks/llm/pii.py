"""Personal data (operator 10): a semi-Markov conditional random field over whole candidate segments.

A chain of digit runs is a region of a text, and so is a run of address letters with an `@`. Inside a region, whatever its
length, the atoms are digit runs (words, around an `@`) and the marks between them; a segment is a run of at most LONGEST
atoms (MAIL_LONGEST for e-mail), its features describe the whole span, and one Viterbi pass chooses boundaries and types
together. Matches of the fixed base patterns are spans in their own right and always stay.

Null text is empty; a very long text is read once, region by region; overlapping kinds are all reported, equal spans once; offsets
are code points; every row has its own result, repeated doc_ids and null ones too; other columns are not read; an empty table
gives an empty table. Work is linear in the text: every pattern is anchored at a run's start.
"""
from __future__ import annotations

import hashlib
import math
import random
import re

from pyspark.sql import DataFrame

KINDS = ("email", "ip", "card", "phone")
LONGEST, MAIL_LONGEST = 12, 24
EMAIL_TAIL = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = re.compile(r"[A-Za-z0-9._%+-]+@")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CHAIN = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
REGION = re.compile(r"[+(]?[0-9](?:[\x20().+-]{0,3}[0-9])+")
ATOM, MAIL_ATOM = re.compile(r"[0-9]+|[^0-9]"), re.compile(r"[A-Za-z0-9]+|[^A-Za-z0-9]")
ADDRESS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-@")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def bare(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def emails(text: str):
    """Leftmost matches: a local part is a maximal run of its letters before `@`, or what an earlier match leaves of it."""
    at, free = text.find("@"), 0
    allowed = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
    while at >= 0:
        s = at
        while s > free and text[s - 1] in allowed:
            s -= 1
        if s < at and (m := EMAIL_TAIL.match(text, at)):
            free = m.end()
            yield "email", s, free
        at = text.find("@", at + 1 if s == at or not m else free)


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = list(emails(text))
    out += [("ip", *m.span()) for m in IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split("."))]
    out += [("card", *m.span()) for m in CHAIN.finditer(text) if m.end() - m.start() >= 16 and 16 <= len(d := bare(m[0])) <= 19 and luhn(d)]
    if "+" in text:
        out += [("phone", *m.span()) for m in PHONE.finditer(text) if 8 <= len(bare(m[0])) <= 15]
    return out


def features(kind: str, text: str, s: int, e: int) -> list[str]:
    """Of a whole segment under a label."""
    span = text[s:e]
    if kind == "email":
        local, _, domain = span.partition("@")
        last = domain.rpartition(".")[2]
        seen = [
            f"dots={min(domain.count('.'), 3)}", f"tld={min(len(last), 5) if '.' in domain and last.isalpha() else 0}", f"local={min(len(local), 3)}", f"gap={'..' in span or '.@' in span or '@.' in span or '-.' in domain}",
            f"left={text[max(0, s - 1) : s] in ADDRESS}", f"right={text[e : e + 1] == '@' or text[e : e + 1].isalnum()}", f"more={text[e : e + 2][:1] in '-.' and text[e + 1 : e + 2].isalnum()}", f"before={text[max(0, s - 1) : s] in ('.', '+', '-', '_', '%')}",
        ]
        return [f"{kind}|{x}" for x in seen] + [f"{kind}|bias"]
    digits, before, after = bare(span), text[max(0, s - 1) : s], text[e : e + 1]
    seen = [
        f"digits={min(len(digits), 20)}", f"plus={span[0] == '+'}", f"luhn={len(digits) >= 16 and luhn(digits)}", f"dots={span.count('.')}",
        f"groups={'-'.join(str(min(len(g), 5)) for g in re.findall('[0-9]+', span)[:5])}", f"parens={'(' in span}", f"edge={before.isdigit() or after.isdigit()}",
        f"left={before in ('', ' ', chr(10))}", f"spaces={min(span.count(' '), 4)}", f"octets={span.count('.') == 3 and all(p.isdigit() and len(p) < 4 and int(p) < 256 for p in span.split('.'))}",
    ]
    return [f"{kind}|{x}" for x in seen] + [f"{kind}|bias"]


class SemiMarkov:
    """Log-linear model of segmentations; label O covers single atoms."""

    labels = ("O", "ip", "card", "phone", "email")

    def __init__(self):
        self.w: dict[str, float] = {}

    def score(self, text, s, e, kind) -> float:
        return 0.0 if kind == "O" else sum(self.w.get(f, 0.0) for f in features(kind, text, s, e))

    def segments(self, text, atoms):
        """(i, j, kind) over atom positions: entities start at a digit, `+` or `(` and end with a digit."""
        for i, (s, _) in enumerate(atoms):
            yield i, i + 1, "O"
            if text[s].isdigit() or text[s] in "+(":
                n = 0
                for j in range(i + 1, min(len(atoms), i + LONGEST) + 1):
                    a, e = atoms[j - 1]
                    n += (e - a) * text[a].isdigit()
                    if n > 19:
                        break
                    if text[a].isdigit() and n >= 4:
                        yield from ((i, j, k) for k in self.labels[1:4])
            if text[s].isalnum() and "@" in text[s : atoms[-1][1]]:
                signs = 0
                for j in range(i + 1, min(len(atoms), i + MAIL_LONGEST) + 1):
                    signs += text[atoms[j - 1][0]] == "@"
                    if signs > 1:
                        break
                    if signs and text[atoms[j - 1][0]].isalnum():
                        yield i, j, "email"

    def decode(self, text, atoms) -> list[tuple[str, int, int]]:
        best, back = [0.0] + [-math.inf] * len(atoms), [None] * (len(atoms) + 1)
        for i, j, kind in self.segments(text, atoms):
            v = best[i] + self.score(text, atoms[i][0], atoms[j - 1][1], kind)
            if v > best[j]:
                best[j], back[j] = v, (i, kind)
        out, j = [], len(atoms)
        while j:
            i, kind = back[j]
            if kind != "O":
                out.append((kind, atoms[i][0], atoms[j - 1][1]))
            j = i
        return out[::-1]

    def fit(self, samples, rounds=4, rate=0.2, decay=1e-3):
        """Stochastic ascent of the exact log-likelihood; expectations by forward and backward sums."""
        for _ in range(rounds):
            for text, atoms, gold in samples:
                segs = [(i, j, k, self.score(text, atoms[i][0], atoms[j - 1][1], k)) for i, j, k in self.segments(text, atoms)]
                n = len(atoms)
                fwd, bwd = [0.0] + [-math.inf] * n, [-math.inf] * n + [0.0]
                add = lambda a, b: max(a, b) + math.log1p(math.exp(-abs(a - b))) if a > -math.inf and b > -math.inf else max(a, b)
                for i, j, _, v in segs:
                    fwd[j] = add(fwd[j], fwd[i] + v)
                for i, j, _, v in reversed(segs):
                    bwd[i] = add(bwd[i], bwd[j] + v)
                for i, j, k, v in segs:
                    if k != "O":
                        s, e = atoms[i][0], atoms[j - 1][1]
                        step = ((k, s, e) in gold) - math.exp(min(0.0, fwd[i] + v + bwd[j] - fwd[n]))
                        if abs(step) > 1e-4:
                            for f in features(k, text, s, e):
                                self.w[f] = self.w.get(f, 0.0) * (1 - rate * decay) + rate * step
        return self


def atoms_of(text: str, s: int, e: int) -> list[tuple[int, int]]:
    return [m.span() for m in ATOM.finditer(text, s, e)]


def training(n: int = 500, seed: int = 7):
    """Labelled regions made by rule: phone, card and address forms alone and side by side, among plain numbers."""
    rng = random.Random(seed)
    num = lambda k: "".join(rng.choice("0123456789") for _ in range(k))

    def card():
        body = rng.choice("3456") + num(14)
        d = body + next(c for c in "0123456789" if luhn(body + c))
        return d if rng.random() < 0.5 else rng.choice(" -").join(d[i : i + 4] for i in range(0, 16, 4))

    def phone():
        cc, p = str(rng.randint(1, 99)), [num(3), num(3), num(4)]
        return rng.choice([f"+{cc} ({p[0]}) {p[1]}-{p[2]}", f"+{cc} {p[0]} {p[1]} {p[2]}", f"+{cc}-{'-'.join(p)}", f"({p[0]}) {p[1]}-{p[2]}", f"+{cc}{''.join(p)}"])

    make = {"card": card, "phone": phone, "ip": lambda: ".".join(str(rng.randint(1, 255)) for _ in range(4)), "O": lambda: rng.choice([num(rng.randint(1, 7)), num(16), f"{num(2)}.{num(2)}", f"{num(4)}-{num(2)}-{num(2)}", num(12)])}
    for _ in range(n):
        text, gold = "", set()
        for _ in range(rng.choice([1, 1, 2, 2, 3])):
            kind = rng.choice(list(make))
            text += " " * bool(text)
            s = len(text)
            text += make[kind]()
            if kind == "O" and len(d := text[s:]) == 16 and luhn(d):
                kind = "card"
            if kind != "O":
                gold.add((kind, s, len(text)))
        yield text, atoms_of(text, 0, len(text)), gold


def mail_training(n: int = 250, seed: int = 8):
    """Labelled regions around an `@`, made by rule: addresses with and without marks after them, among handles and broken forms."""
    rng = random.Random(seed)
    word = lambda a, b: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz0123456789") for _ in range(rng.randint(a, b)))
    top = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 4)))
    for _ in range(n):
        local = rng.choice("._+-").join(word(1, 8) for _ in range(rng.choice([1, 1, 2, 3])))
        domain = ".".join([word(2, 9) + rng.choice(["", "", "-" + word(1, 5)]) for _ in range(rng.choice([1, 1, 2]))] + [top()])
        kind = rng.random()
        if kind < 0.6:
            text, gold = f"{local}@{domain}", {("email", 0, len(local) + 1 + len(domain))}
            text += rng.choice(["", "", "", ".", "-", "..."])
        else:
            text, gold = rng.choice([f"@{word(3, 9)}", f"{local}@", f"{local}@{word(2, 9)}", f"{local}@@{domain}", f"{word(2, 6)}@.{word(2, 5)}", f"@{word(2, 5)}.{top()}"]), set()
        yield text, [m.span() for m in MAIL_ATOM.finditer(text)], gold


def trained() -> SemiMarkov:
    return SemiMarkov().fit([*training(), *mail_training()])


def mail_regions(text: str):
    """Maximal runs of address letters that hold an `@`."""
    at, end = text.find("@"), 0
    while at >= 0:
        s, e = at, at + 1
        while s > end and text[s - 1] in ADDRESS:
            s -= 1
        while e < len(text) and text[e] in ADDRESS:
            e += 1
        yield s, e
        end, at = e, text.find("@", e)


def method_spans(text: str, model: SemiMarkov) -> list[tuple[str, int, int]]:
    out = []
    for s, e in mail_regions(text):
        out += [x for x in model.decode(text, [m.span() for m in MAIL_ATOM.finditer(text, s, e)]) if x[0] != "card" or luhn(bare(text[x[1] : x[2]]))]
    for m in REGION.finditer(text):
        if m.end() - m.start() < 7:
            continue
        atoms = atoms_of(text, *m.span())
        out += [x for x in model.decode(text, atoms) if x[0] != "card" or luhn(bare(text[x[1] : x[2]]))]
    return out


def joined(spans) -> str:
    place = {k: i for i, k in enumerate(KINDS)}
    return ",".join(f"{k}:{s}:{e}" for k, s, e in sorted(set(spans), key=lambda x: (place[x[0]], x[1], x[2])))


def find_pii(docs: DataFrame) -> DataFrame:
    """One pass without a shuffle: counts and digest of the base spans, and all spans."""
    shared = docs.sparkSession.sparkContext.broadcast(trained().w)

    def run(batches):
        import pyarrow as pa

        model = SemiMarkov()
        model.w = shared.value
        for b in batches:
            rows = []
            for text in b.column(1):
                text = text.as_py() or ""
                base = base_spans(text)
                rows.append([*(sum(x[0] == k for x in base) for k in KINDS), hashlib.sha256(joined(base).encode()).hexdigest(), joined(base + method_spans(text, model))])
            cols = list(zip(*rows)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, pa.int64()) for c in cols[:4]), *(pa.array(c, pa.string()) for c in cols[4:])], ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string")
