"""Personal data: candidate spans from generous patterns, judged by boosted trees over format and context."""

from __future__ import annotations

import re
from bisect import bisect_right
from collections.abc import Iterable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tricount.llm.boosting import BoostedTrees

#: Kinds in the order in which spans with equal starts are listed.
KINDS = ("email", "ip", "card", "phone")
#: Thresholds are the least calibrated probabilities with which this share of the accepted held-out examples is personal data.
PRECISION = 0.98
#: Candidates that the trees judge at a time.
JUDGED = 20_000
#: Characters of context on each side of a candidate.
CONTEXT = 40

# The base patterns. Look-behinds and possessive runs only keep them from trying again inside a run that has failed.
_LOCAL = "A-Za-z0-9._%+-"
_DOMAIN = re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]+)+")
_LOCAL_RUN = re.compile(rf"[{_LOCAL}]+\Z")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]+){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")

# Generators of further candidates.
_HEX = "[0-9A-Fa-f]{1,4}"
_LOOSE = {
    "email": re.compile(rf"(?<![{_LOCAL}])[A-Za-z0-9._+-]{{1,64}}(?i:\x20?(?:@|\(at\)|\[at\])\x20?|\x20at\x20)[A-Za-z0-9-]{{1,63}}(?:(?i:\.|\x20?(?:\(dot\)|\[dot\])\x20?|\x20dot\x20)[A-Za-z0-9-]{{1,63}}){{1,4}}"),
    "ip": re.compile(rf"(?<![0-9A-Za-z:])(?:(?:{_HEX}:){{3,7}}{_HEX}(?![0-9A-Za-z:])|(?:{_HEX}(?::{_HEX}){{0,6}}::(?:{_HEX}(?::{_HEX}){{0,6}})?|::{_HEX}(?::{_HEX}){{0,6}})(?!:{{0,2}}[0-9A-Za-z]))"),
    "card": re.compile(r"(?<![0-9A-Za-z])[0-9]{4}(?:[\x20./-]?[0-9]{2,6}){2,4}(?![0-9A-Za-z])"),
    "phone": re.compile(r"(?<![0-9A-Za-z+.])\(?[0-9]{2,4}\)?(?:[\x20./-]{1,2}[0-9]{2,4}){2,4}(?![0-9A-Za-z])"),
}
_WORDS = {
    "email": re.compile(r"mail|contact|write|reach|reply|correo|courriel", re.I),
    "ip": re.compile(r"\bip\b|host|server|address|client|login|addr", re.I),
    "card": re.compile(r"card|visa|master|credit|debit|amex|pay|karte|carte|tarjeta|iban", re.I),
    "phone": re.compile(r"phone|call|tel\b|tel[.:]|mobile|fax|cell|dial|whatsapp|handy|t[eé]l", re.I),
}
_OTHER = re.compile(r"version|isbn|order|invoice|serial|sku|page|article|\bid\b|date|total|price|chapter|sha|uuid|build|part|\bmac\b|score|sum|sold|look|meet|open|room", re.I)
_ENDS = re.compile(r"(?i)(?:com|org|net|edu|gov|info|io|de|fr|es|it|uk|us|eu|ch|at|nl)\Z")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the fixed patterns, leftmost and without overlap within a kind, sorted. Time grows with the text's length alone."""
    out = []
    at = floor = 0
    while (at := text.find("@", at)) >= 0:
        start = at
        while start > floor and (c := text[start - 1]).isascii() and (c.isalnum() or c in "._%+-"):
            start -= 1
        m = _DOMAIN.match(text, at) if start < at else None
        if m:
            out.append((start, 0, m.end()))
            at = floor = m.end()
        else:
            at += 1
            floor = at
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
            out.append((m.start(), 1, m.end()))
    for m in _CARD.finditer(text):
        d = _digits(m[0])
        if 14 <= len(d) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 10 <= len(_digits(m[0])) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


def candidates(text: str) -> list[tuple[int, int, int]]:
    """Spans of the generous patterns; they may overlap each other and base spans."""
    out = []
    for k, kind in enumerate(KINDS):
        if kind == "ip" and ":" not in text:
            continue
        out += [(m.start(), k, m.end()) for m in _LOOSE[kind].finditer(text)]
    return out


def describe(text: str, start: int, kind: int, end: int) -> list[float]:
    """Format and context of a candidate as numbers."""
    span, d = text[start:end], _digits(text[start:end])
    before, after = text[max(0, start - CONTEXT) : start], text[end : end + CONTEXT]
    groups = [len(g) for g in re.findall("[0-9]+", span)]
    letters = sum(c.isalpha() for c in span)
    return [
        len(span), len(d), letters / len(span), len(groups), max(groups, default=0), min(groups, default=0),
        len(set(re.sub(r"[0-9A-Za-z]", "", span))), float(luhn(d)) if len(d) >= 12 else -1.0, len(set(d)) / max(len(d), 1),
        float(d[:1] in "3456") if d else 0.0, float("(" in span), span.count("."), span.count("-"), span.count(" "),
        float(bool(_WORDS[KINDS[kind]].search(before))), float(bool(_WORDS[KINDS[kind]].search(after))), float(bool(_OTHER.search(before))),
        float("@" in span), float(before[-1:] in "#$=_/" and bool(before)), float(after[:1] in "%_=/" and bool(after)),
        float(bool(_WORDS[KINDS[kind]].search(before[-16:]))), float(bool(_OTHER.search(before[-16:]))), float(bool(_ENDS.search(span))), float(any(c in "._+-0123456789" for c in span[: span.find(" ")])),
        float(":" in span), float("::" in span), float(d[:1] == "0"), float(bool(re.search(r"(?i)[(\[](?:at|dot)[)\]]| dot ", span))),
    ]


def _examples(kind: int, n: int, seed: int) -> tuple[list[list[float]], list[int], list[tuple[str, int, int]]]:
    """Labelled candidates from a seeded writer of sentences, as numbers and as (text, start, end): personal data in the forms people write, and numbers or phrases of the same shapes that only their context tells apart."""
    rng = np.random.default_rng(seed)
    pick = lambda xs: xs[int(rng.integers(len(xs)))]
    num = lambda k: "".join(str(x) for x in rng.integers(0, 10, k))
    word = lambda: "".join(pick(list("abcdeghilmnoprstuv")) for _ in range(int(rng.integers(2, 8))))

    def card(good: bool) -> str:
        body = pick("3456") + num(14)
        return next(body + c for c in "0123456789" if luhn(body + c) == good)

    def made(good: bool) -> tuple[str, str]:
        if kind == 0:
            tail = pick(["com", "org", "net", "de", "fr", "es", "io"])
            if good:
                at, dot = pick([("(at)", "(dot)"), ("[at]", "[dot]"), (" (at) ", " (dot) "), (" at ", " dot "), (" @ ", "."), ("@", " dot "), (" at ", ".")])
                plain = (at, dot) == (" at ", ".")
                name = f"{word()}{pick(['.', '_', '-'] if plain else ['.', '_', ''])}{word()}{pick(['', num(2)])}"
                return f"{name}{at}{word()}{dot}{tail}", pick(["mail me: ", "contact ", "write to ", "reach me, "] + [""] * (not plain))
            return pick([f"{word()} at {word()}.{word()}", f"{word()} @ {word()}.{num(2)}", f"{num(1)} at {num(2)}.{num(2)}", f"{word()} at {word()}.{tail}", f"{word()} @ {num(1)}.{num(2)}"]), pick(["look ", "", "sold ", "version ", "it was ", "meet ", "open "])
        if kind == 1:
            if good:
                x = ["%x" % x for x in rng.integers(4096, 65536, 8)]
                a, b = int(rng.integers(1, 5)), int(rng.integers(0, 4))
                return pick([":".join(x), f"{':'.join(x[:a])}::{':'.join(x[a : a + b])}"]), pick(["host ", "ip ", "from client ", "", "login "])
            mac = ":".join("%02x" % x for x in rng.integers(0, 256, 6))
            return pick([":".join(num(2) for _ in range(int(rng.integers(4, 7)))), ":".join(num(1) for _ in range(4)), f"{pick('abcdef')}::{pick('abcdef')}", mac]), pick(["at ", "chapter ", "", "score ", "time ", "mac ", "host "])
        if kind == 2:
            if good:
                c = card(True)
                return pick([c, f"{c[:4]} {c[4:8]} {c[8:12]} {c[12:]}", f"{c[:4]}.{c[4:8]}.{c[8:12]}.{c[12:]}", f"{c[:4]}/{c[4:8]}/{c[8:12]}/{c[12:]}"]), pick(["card ", "visa: ", "pay with ", "", "my credit card is "])
            n, c = num(16), card(False)
            return pick([c, n, f"{num(4)}.{num(2)}.{num(2)}", f"{num(4)}-{num(2)}-{num(2)}", num(12), num(10), f"{c[:4]}.{c[4:8]}.{c[8:12]}.{c[12:]}", f"{c[:4]}/{c[4:8]}/{c[8:12]}/{c[12:]}"]), pick(["order ", "isbn ", "serial ", "", "on ", "id ", "the ", "card "])
        a, b, c = num(3), num(3), num(4)
        strong, weak = [f"({a}) {b}-{c}", f"{a}-{b}-{c}"], [f"{a}.{b}.{c}", f"0{num(2)} {num(4)} {num(4)}", f"{a} {b} {c}", f"({a}) {b} {c}"]
        if good:
            lead = pick(["call ", "phone: ", "tel. ", "mobile ", "fax ", "cell ", "dial "])
            return (pick(strong), pick([lead, lead, "", "ask at "])) if rng.integers(2) else (pick(weak), lead)
        dates = [f"{num(4)}-{num(2)}-{num(2)}", f"{num(2)}.{num(2)}.{num(4)}", f"{num(2)}/{num(2)}/{num(2)}", f"{num(3)}-{num(2)}-{num(3)}", f"{num(3)} {num(3)} {num(3)}", " ".join(num(3) for _ in range(int(rng.integers(3, 6)))), f"{num(3)}-{num(1)}{num(1)}-{num(5)}"]
        other = pick(["order ", "part ", "invoice ", "total ", "page ", "serial ", "id ", "sum ", "version ", "isbn ", "room "])
        return (pick([*strong, *weak]), other) if rng.integers(2) else (pick(dates), pick(["on ", "date ", "", "the ", other]))

    xs, ys, told = [], [], []
    while len(ys) < n:
        good = bool(rng.integers(2))
        span, lead = made(good)
        head = f"{word()} {word()} {lead}"
        text = f"{head}{span} {word()} {word()}."
        xs.append(describe(text, len(head), kind, len(head) + len(span)))
        ys.append(int(good))
        told.append((text, len(head), len(head) + len(span)))
    return xs, ys, told


@cache
def trained() -> dict[str, tuple[BoostedTrees, float]]:
    """A model and a threshold for each kind. The labelled examples are written by a seeded generator, so every driver trains the same trees. Of every four examples two grow the trees, one calibrates them and one picks the threshold."""
    out = {}
    for k, kind in enumerate(KINDS):
        xs, ys, _ = _examples(k, 1600, 100 + k)
        x, y, turn = np.array(xs), np.array(ys, dtype=float), np.arange(len(ys)) % 4
        model = BoostedTrees(trees=25).fit(x[turn < 3], y[turn < 3], turn[turn < 3] == 0)
        p, truth = model.probability(x[turn == 3]), y[turn == 3]
        order = np.argsort(-p, kind="stable")
        precise = np.flatnonzero(np.cumsum(truth[order]) >= PRECISION * np.arange(1, len(order) + 1))
        out[kind] = (model, max(0.5, float(p[order][precise[-1]])) if len(precise) else 1.0)
    return out


def planted(n: int = 400, seed: int = 900) -> dict[str, tuple[float, float]]:
    """(precision, recall) by kind of what base patterns and accepted candidates mark together, on sentences written from another seed than the examples of training. A planted span counts as found when all of it is marked; a look-alike that is touched counts against precision."""
    out, models = {}, trained()
    for k, kind in enumerate(KINDS):
        _, ys, told = _examples(k, n, seed + k)
        hit = false = 0
        for (text, a, b), good, (own, more) in zip(told, ys, judged([t for t, _, _ in told], models), strict=True):
            spans = [(x, y) for x, j, y in own + more if j == k and x < b and a < y]
            hit += bool(good and any(x <= a and b <= y for x, y in spans))
            false += bool(not good and spans)
        out[kind] = (hit / max(hit + false, 1), hit / max(sum(ys), 1))
    return out


class _Taken:
    """Stretches of a text without overlap; a stretch is looked up and put in by bisection."""

    def __init__(self, spans: list[tuple[int, int, int]] = ()) -> None:
        self.start, self.end = [], []
        for a, _, b in spans:  # sorted by start; those that touch become one
            if self.end and a < self.end[-1]:
                self.end[-1] = max(self.end[-1], b)
            else:
                self.start.append(a)
                self.end.append(b)

    def touches(self, a: int, b: int) -> bool:
        at = bisect_right(self.end, a)
        return at < len(self.start) and self.start[at] < b

    def add(self, a: int, b: int) -> None:
        at = bisect_right(self.end, a)
        self.start.insert(at, a)
        self.end.insert(at, b)


def judged(texts: Iterable[str], models: dict[str, tuple[BoostedTrees, float]]) -> Iterator[tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]]:
    """(base spans, added spans) of each text in turn. Added are candidates that the trees accept and that touch no base span; of overlapping ones the likelier, then the earlier, then the longer stays.

    Candidates of several texts are judged at a time, so a model runs once for many; work grows with the number of candidates times its logarithm.
    """
    waiting: list[tuple[list, list]] = []
    held = 0

    def told() -> Iterator[tuple[list, list]]:
        found: list[list] = [[] for _ in waiting]
        for k, kind in enumerate(KINDS):
            mine = [(t, a, b, x) for t, (_, more) in enumerate(waiting) for a, j, b, x in more if j == k]
            if mine:
                model, least = models[kind]
                for (t, a, b, _), p in zip(mine, model.probability(np.array([m[3] for m in mine])).tolist(), strict=True):
                    if p >= least:
                        found[t].append((-p, a, a - b, k, b))
        for (own, _), accepted in zip(waiting, found, strict=True):
            taken, out = _Taken(), []
            for _, a, _, k, b in sorted(accepted):
                if not taken.touches(a, b):
                    taken.add(a, b)
                    out.append((a, k, b))
            yield own, out

    for text in texts:
        own = base_spans(text)
        taken = _Taken(own)
        more = [(a, k, b, describe(text, a, k, b)) for a, k, b in candidates(text) if not taken.touches(a, b)]
        waiting.append((own, more))
        held += len(more) + 1
        if held >= JUDGED:
            yield from told()
            waiting, held = [], 0
    yield from told()


def added_spans(text: str, models: dict[str, tuple[BoostedTrees, float]]) -> list[tuple[int, int, int]]:
    return next(iter(judged([text], models)))[1]


def find_personal(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, base and spans, each an array of (kind, start, end) by start and then kind, in code points, end exclusive.

    `base` has the fixed patterns; `spans` has these and what the trees accept among other candidates. Null and empty texts have none. Rows are
    independent: repeated rows get the same spans, a null id passes through. An empty table gives no rows. Other columns are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(trained())
    span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
    told = lambda spans: [{"kind": KINDS[k], "start": a, "end": b} for a, k, b in sorted(spans)]

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = shared.value
        for batch in batches:
            base, spans = [], []
            for own, more in judged((text.as_py() or "" for text in batch.column("text")), models):
                base.append(told(own))
                spans.append(told(own + more))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(base, span), pa.array(spans, span)], names=["doc_id", "base", "spans"])

    kind = "array<struct<kind:string,start:long,end:long>>"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(found, f"doc_id long, base {kind}, spans {kind}")


def redact(docs: DataFrame) -> DataFrame:
    """doc_id and text with every span replaced by its kind in brackets; of overlapping spans the one that starts first. Null texts stay null, empty ones empty; rows are independent, so repeated rows agree. An empty table gives no rows."""
    shared = docs.sparkSession.sparkContext.broadcast(trained())

    def replaced(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out, texts = [], batch.column("text").to_pylist()
            for text, (own, more) in zip(texts, judged((t or "" for t in texts), shared.value), strict=True):
                if text:
                    parts, at = [], 0
                    for a, k, b in sorted(own + more):
                        if b > at:
                            parts += [text[at : max(a, at)], f"[{KINDS[k]}]"] if a >= at else []
                            at = b
                    text = "".join(parts) + text[at:]
                out.append(text)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out, pa.string())], names=["doc_id", "text"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(replaced, "doc_id long, text string")


def digest(found: DataFrame) -> DataFrame:
    """Counts of the base spans by kind, the hash of their list, and the list of all spans as text."""
    listed = lambda column: F.array_join(F.transform(column, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    of_kind = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long")
    counts = [of_kind(k).alias(f"n_{k}") for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(listed("base").cast("binary"), 256).alias("base_sha256"), listed("spans").alias("spans"))
