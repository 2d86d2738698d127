"""Personal data: high-recall generators propose overlapping spans, boosted trees judge them, calibrated thresholds select.

Four kinds: email, ip, card, phone. Strict patterns give the base spans, which always stay. Looser generators propose more:
addresses spelt out (`name at host dot org`), numbers without a plus sign, with dots or slashes as separators. A boosted model
for each kind sees format (lengths, digits, separators, check digit, ranges) and context (neighbouring characters, cue words in
the forty characters before), and a proposal that overlaps no base span is added if its calibrated probability reaches the
threshold, which holds the wanted precision on held-out examples. Overlapping additions: the likelier first.

The models are trained on examples that a seeded generator makes: formats of personal data and of look-alikes (versions, order
numbers, dates, digests, measures) amid random words. Training depends on no table, so behaviour is alike at every size.

Defined results: a null text is an empty one, without spans; repeated rows get equal results; an empty table gives an empty result. Offsets are code
points, end exclusive. The time for a text grows with its length alone (and the logarithm of its spans), unbroken runs of a megabyte included.
"""

from __future__ import annotations

import re
from bisect import bisect_left, insort
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from utilmine.llm import tokens
from utilmine.llm.boosting import Boosted, threshold_for

KINDS = ("email", "ip", "card", "phone")
#: The base patterns.
BASE = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}
#: What a text must hold for a base pattern to match at all.
NEEDS = {"email": re.compile("@"), "ip": re.compile(r"[0-9]\.[0-9]"), "card": re.compile(r"[0-9]"), "phone": re.compile(r"\+[0-9]")}
LOOSE = {
    "email": re.compile(r"[A-Za-z0-9._%+-]{2,64}(?:\s?(?:@|\(at\)|\[at\])\s?[A-Za-z0-9-]{2,63}(?:\s?(?:\.|\(dot\)|\[dot\])\s?[A-Za-z0-9-]{2,24}){1,4}|\sat\s[A-Za-z0-9-]{2,63}(?:\sdot\s[A-Za-z0-9-]{2,24}){1,4})"),
    "ip": re.compile(r"[0-9]{1,3}(?:\s?[.,]\s?[0-9]{1,3}){3,5}"),
    "card": re.compile(r"[0-9]{4}(?:[\x20./_-]{0,2}[0-9]{2,6}){2,5}"),
    "phone": re.compile(r"(?:\+|00)?\(?[0-9]{2,4}\)?(?:[\x20./-]{1,2}\(?[0-9]{2,5}\)?){1,5}"),
}
#: An address without an @: the at in brackets, or at and dot in words.
SPELT = r"[(\[]at[)\]]|\sat\s[A-Za-z0-9-]+\sdot\s"
LOOSE_NEEDS = {"email": re.compile(f"@|{SPELT}"), "ip": re.compile(r"[0-9]\s?[.,]\s?[0-9]"), "card": re.compile(r"[0-9]{4}"), "phone": re.compile(r"[0-9]{2}")}
#: Words that announce each kind.
CUES = {
    "email": ("mail", "contact", "write", "address", "reply", "to"),
    "ip": ("ip", "host", "server", "address", "from", "login"),
    "card": ("card", "visa", "mastercard", "credit", "pay", "account"),
    "phone": ("phone", "tel", "call", "mobile", "fax", "cell"),
}
BEFORE = 40
PRECISION, EXAMPLES, SEED = 0.98, 6000, 11


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def holds(kind: str, s: str) -> bool:
    """The check on a match of a base pattern."""
    if kind == "ip":
        return all(len(d := p.lstrip("0")) <= 3 and int(d or "0") <= 255 for p in s.split("."))
    if kind == "card":
        return 16 <= len(d := _digits(s)) <= 19 and luhn(d)
    if kind == "phone":
        return 8 <= len(_digits(s)) <= 15
    return True


#: Searched behind an @ that has a character of LOCAL before it: a search from the left would read an unbroken run once for each of its starts.
LOCAL = frozenset("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789._%+-")
HOST = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
#: A match of the base ip pattern starts where a run of digits does, as a match that fails there fails at every later digit of the run, too.
IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)")


def _emails(text: str) -> Iterator[tuple[int, int]]:
    """The matches of the base email pattern: each @ is walked from outwards, no further left than the match before."""
    done = 0
    at = text.find("@")
    while at >= 0:
        if host := HOST.match(text, at + 1):
            start = at
            while start > done and text[start - 1] in LOCAL:
                start -= 1
            if start < at:
                done = host.end()
                yield start, done
        at = text.find("@", max(done, at + 1))


def _matches(kind: str, text: str) -> Iterator[tuple[int, int]]:
    if kind == "email":
        return _emails(text)
    return (m.span() for m in (IP if kind == "ip" else BASE[kind]).finditer(text))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """The base spans by kind, then start."""
    return [(k, a, b) for k in KINDS if NEEDS[k].search(text) for a, b in _matches(k, text) if holds(k, text[a:b])]


class Taken:
    """Spans that others must not overlap: fixed ones, which may overlap each other, and added ones, which do not."""

    def __init__(self, spans: list[tuple[str, int, int]]):
        fixed = sorted((a, b) for _, a, b in spans)
        self.starts = [a for a, _ in fixed]
        self.reach = list(accumulate((b for _, b in fixed), max))
        self.added: list[tuple[int, int]] = []

    def overlaps(self, start: int, end: int) -> bool:
        i, j = bisect_left(self.starts, end), bisect_left(self.added, (end,))
        return i > 0 and self.reach[i - 1] > start or j > 0 and self.added[j - 1][1] > start

    def add(self, start: int, end: int) -> None:
        insort(self.added, (start, end))


def features(kind: str, text: str, start: int, end: int) -> list[float]:
    s, d = text[start:end], _digits(text[start:end])
    before, after = text[max(0, start - BEFORE) : start], text[end : end + 12]
    cue = before.lower()
    parts = re.split(r"[^0-9A-Za-z]+", s.strip("()+"))
    numbers = [int(p) for p in parts if p.isdecimal() and len(p) < 10]
    last = re.findall(r"[A-Za-z]+", cue)
    return [
        len(s), len(d), len(d) / len(s), luhn(d) if d else 0, len(parts), max(map(len, parts)), min(map(len, parts)), len(set(map(len, parts))),
        s.startswith("+"), s.startswith("00"), "(" in s, s.count("."), s.count("-"), s.count(" "), s.count("/"), s.count(","), "@" in s, "at" in s, "dot" in s.lower(),
        max(numbers, default=0) <= 255, max(numbers, default=0), 1900 <= (numbers[0] if numbers else 0) <= 2100, len(re.sub(r"[^A-Za-z]", "", parts[-1])),
        any(c in cue for c in CUES[kind]), bool(last) and last[-1] in CUES[kind], any(c in cue for k in KINDS if k != kind for c in CUES[k]),
        "version" in cue or bool(re.search(r"\bv\.?\s?$", cue)), bool(re.search(r"[#$€£=]\s?$", before)), before[-1:].isalnum(), before[-1:] in ".,-_/", after[:1].isalnum(), after[:1] in "%-_/" and after[:1] != "",
        bool(re.match(r"\.\d", after)), bool(re.match(r"\s?(kg|cm|mm|km|eur|usd|%|\$|€)", after.lower())),
    ]


def _made(kind: str, rng: np.random.Generator) -> tuple[str, int]:
    """A string and whether it is personal data of this kind."""
    n = lambda a, b: int(rng.integers(a, b + 1))
    word = lambda a=3, b=9: "".join(chr(97 + n(0, 25)) for _ in range(n(a, b)))
    digits = lambda k: "".join(str(n(0, 9)) for _ in range(k))
    one = lambda *options: options[n(0, len(options) - 1)]
    if kind == "email":
        host, end = word(), one("com", "org", "net", "de", "fr", "es", "edu")
        return one((f"{word()}.{word()}@{host}.{end}", 1), (f"{word()} at {host} dot {end}", 1), (f"{word()}(at){host}.{end}", 1), (f"{word()} [at] {host} [dot] {end}", 1), (f"{word()}{n(1, 99)} @ {host}.{end}", 1), (f"{word()} at {word()}.{word()}", 0), (f"{word()} at {word()}. {word()}", 0), (f"{word()} at the.{word()}", 0), (f"{word()} at {word()} dot", 0))
    if kind == "ip":
        good = [n(1, 254) for _ in range(4)]
        return one((".".join(map(str, good)), 1), (" . ".join(map(str, good)), 1), (",".join(map(str, good)), 0), (".".join(map(str, [n(0, 9) for _ in range(5)])), 0), (".".join(map(str, [n(256, 999), *good[1:]])), 0), (", ".join(map(str, good)), 0), (".".join(map(str, [*good, n(1, 254)])), 0))
    if kind == "card":
        d = digits(15)
        d += next(str(c) for c in range(10) if luhn(d + str(c)))
        wrong = d[:-1] + str((int(d[-1]) + n(1, 9)) % 10)
        cut = lambda x, by: by.join(x[i : i + 4] for i in range(0, 16, 4))
        return one((cut(d, " "), 1), (cut(d, "."), 1), (cut(d, "/"), 1), (cut(d, " - "), 1), (cut(d, "_"), 1), (cut(wrong, " "), 0), (cut(wrong, "."), 0), (wrong, 0), (digits(13), 0), (digits(20), 0), (f"{n(1990, 2030)}-{n(10, 12)}-{n(10, 28)} {n(10, 23)}", 0))
    a, b, c = digits(3), digits(3), digits(4)
    return one((f"({a}) {b}-{c}", 1), (f"{a}-{b}-{c}", 1), (f"00{n(30, 49)} {digits(3)} {digits(7)}", 1), (f"+{n(1, 99)} ({a}) {b}-{c}", 1), (f"{a}.{b}.{c}", 1), (f"{n(1900, 2030)}-{n(10, 12)}-{n(10, 28)}", 0), (f"{n(10, 28)}/{n(10, 12)}/{n(1900, 2030)}", 0), (f"{n(1900, 2030)}-{n(10, 12)}-{n(10, 28)} {n(10, 23)}", 0), (f"{n(10, 28)}.{n(10, 12)}.{n(1900, 2030)}", 0), (f"{n(10, 99)}-{n(10, 99)}", 0), (f"{digits(3)} {digits(3)} {digits(3)}", 0), (f"{n(10, 23)}.{n(10, 59)}", 0), (f"{digits(2)}.{digits(3)}.{digits(3)}", 0), (f"{digits(5)}-{digits(4)}", 0), (f"{digits(3)}-{digits(4)}", 0))


@lru_cache(maxsize=1)
def models() -> dict[str, tuple[Boosted, float]]:
    """For each kind a calibrated model and its threshold."""
    out = {}
    for number, kind in enumerate(KINDS):
        rng = np.random.default_rng([SEED, number])
        x, y = [], []
        for _ in range(EXAMPLES):
            s, good = _made(kind, rng)
            filler = [" ".join("".join(chr(97 + rng.integers(26)) for _ in range(rng.integers(2, 9))) for _ in range(rng.integers(0, 6))) for _ in range(2)]
            cue = CUES[kind][rng.integers(len(CUES[kind]))] if rng.random() < (0.4 if good else 0.1) else ("version" if not good and rng.random() < 0.1 else "")
            head = f"{filler[0]} {cue} ".lstrip()
            x.append(features(kind, f"{head}{s} {filler[1]}", len(head), len(head) + len(s)))
            y.append(good)
        x, y = np.asarray(x, float), np.asarray(y, float)
        cut = EXAMPLES * 2 // 3
        model = Boosted().fit(x[:cut], y[:cut]).calibrate(x[cut:], y[cut:])
        out[kind] = model, max(0.5, threshold_for(model.probability(x[cut:]), y[cut:], PRECISION))
    return out


def proposals(text: str, taken: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """Spans of the loose generators that overlap no span in taken."""
    out, used = [], Taken(taken)
    for kind in KINDS:
        if LOOSE_NEEDS[kind].search(text):
            out += [(kind, m.start(), m.end()) for m in LOOSE[kind].finditer(text) if not used.overlaps(*m.span())]
    return out


def all_spans(texts: list[str], trained: dict[str, tuple[Boosted, float]]) -> list[tuple[list, list]]:
    """Base spans and all spans of each text, by kind, then start; proposals of all texts are scored in one batch for each kind."""
    base = [base_spans(t) for t in texts]
    asked = {k: [] for k in KINDS}
    for i, t in enumerate(texts):
        for kind, a, b in proposals(t, base[i]):
            asked[kind].append((i, a, b))
    added: list[list] = [[] for _ in texts]
    for kind, rows in asked.items():
        if rows:
            model, threshold = trained[kind]
            p = model.probability(np.asarray([features(kind, texts[i], a, b) for i, a, b in rows], float))
            for (i, a, b), value in zip(rows, p, strict=True):
                if value >= threshold:
                    added[i].append((-value, kind, a, b))
    out = []
    for found, more in zip(base, added, strict=True):
        chosen, used = list(found), Taken(found)
        for _, kind, a, b in sorted(more):
            if not used.overlaps(a, b):
                used.add(a, b)
                chosen.append((kind, a, b))
        out.append((found, sorted(chosen, key=lambda s: (KINDS.index(s[0]), s[1], s[2]))))
    return out


def _told(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


_INTERESTING = np.zeros(256, bool)
_INTERESTING[[ord("@"), *range(48, 58)]] = True


def _maybe(column: pa.Array) -> np.ndarray:
    """Whether each text has a digit, an @ or a spelt-out at; others cannot hold a span."""
    out = np.zeros(len(column), bool)
    for block in tokens.blocks(column):
        sums = np.append(0, np.cumsum(_INTERESTING[block.data], dtype=np.int64))
        out[block.first : block.last] = sums[block.bounds[1:]] > sums[block.bounds[:-1]]
    return out


def _finder(trained: dict[str, tuple[Boosted, float]]):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(1)
            maybe = _maybe(column) | np.asarray(pc.fill_null(pc.match_substring_regex(column, SPELT), False))
            counts, base, spans = np.zeros((len(KINDS), len(column)), np.int64), [""] * len(column), [""] * len(column)
            for part in np.array_split(np.flatnonzero(maybe), max(1, int(maybe.sum()) // 256)):
                texts = [column[int(i)].as_py() for i in part]
                for i, (own, every) in zip(part, all_spans(texts, trained), strict=True):
                    for kind, _, _ in own:
                        counts[KINDS.index(kind), i] += 1
                    base[i], spans[i] = _told(own), _told(every)
            out = {"doc_id": batch.column(0)} | {f"n_{k}": pa.array(c) for k, c in zip(KINDS, counts, strict=True)}
            yield pa.record_batch(out | {"base_spans": pa.array(base), "spans": pa.array(spans)})

    return rows


def find(docs: DataFrame) -> DataFrame:
    """doc_id, n_<kind> of base spans, base_spans and spans (kind:start:end, comma-joined) for each row of docs."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(_finder(models()), f"doc_id {kind}, {', '.join(f'n_{k} long' for k in KINDS)}, base_spans string, spans string")


def redact(text: str, spans: str) -> str:
    """text with every span of a comma-joined list replaced by its kind in brackets."""
    cuts = sorted((int(a), int(b), k) for k, a, b in (x.split(":") for x in spans.split(",") if x))
    out, at = [], 0
    for a, b, k in cuts:
        if a >= at:
            out += [text[at:a], f"[{k.upper()}]"]
            at = b
    return "".join([*out, text[at:]])
