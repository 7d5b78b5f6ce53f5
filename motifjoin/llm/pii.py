"""Personal data by candidate gradient boosting.

High-recall generators read every text and propose overlapping spans:
number-like runs and their parts, addresses written plainly or spelt out, keyed
secrets, long tokens, all to their ends. Boosted trees score every candidate by
its format and its context; calibrated thresholds, one per kind and chosen on
examples that were not trained on, select redactions, the most probable first
and none overlapping another. Exact rules for e-mail, IPv4, payment card
and phone numbers run beside them; what they find always stays, and the model
adds spans where they found none.

The trees are trained here, on the driver, on generated examples of a fixed
seed: formats in contexts, with look-alikes (dates, versions, prices, ranges,
ISBNs) as the negative class. Nothing is learned from the corpus.

All scans are linear in the length of the text; candidates are sorted and chosen by bisection. Defined results: null text is
empty and has no spans; null ``doc_id`` and repeated rows are scanned each;
other columns are ignored. Offsets count code points, ends are exclusive.
"""

from __future__ import annotations

import hashlib
import random
import re
from bisect import bisect_left
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: The kinds in order (those of the exact rules first) and the exact rules' patterns.
BASE_KINDS, ADDED_KINDS = ("email", "ip", "card", "phone"), ("secret", "id")
KINDS = BASE_KINDS + ADDED_KINDS
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
DOTTED = re.compile(r"[0-9]+(?:\.[0-9]+)*")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_MAYBE = re.compile(r"[0-9@]")
_DIGIT = re.compile(r"[0-9]")

Span = tuple[int, int, str]


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        n = ord(c) - 48
        total += n if k % 2 == 0 else 2 * n - 9 * (n > 4)
    return total % 10 == 0


def _emails(text: str) -> Iterator[Span]:
    done, at = 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > done and text[begin - 1] in LOCAL:
            begin -= 1
        if begin < at and (m := DOMAIN.match(text, at + 1)):
            yield begin, m.end(), "email"
            done = m.end()
        at = text.find("@", max(at + 1, done))


def _addresses(text: str) -> Iterator[Span]:
    for m in DOTTED.finditer(text):
        at, parts = m.start(), m.group().split(".")
        for k in range(0, len(parts) - 3, 4):
            four = parts[k : k + 4]
            end = at + sum(map(len, four)) + 3
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in four):
                yield at, end, "ip"
            at = end + 1


def base_spans(text: str | None) -> list[Span]:
    """What the exact rules find, per kind leftmost and without overlap, by start and kind."""
    if not text or not _MAYBE.search(text):
        return []
    out = list(_emails(text)) if "@" in text else []
    if _DIGIT.search(text):
        out += _addresses(text)
        for m in CARD.finditer(text):
            digits = m.group().replace(" ", "").replace("-", "")
            if 14 <= len(digits) <= 19 and luhn(digits):
                out.append((m.start(), m.end(), "card"))
        if "+" in text:
            out += [(m.start(), m.end(), "phone") for m in PHONE.finditer(text) if 10 <= len(_DIGIT.findall(m.group())) <= 15]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


_AT = re.compile(r" ?[(\[]at[)\]] ?", re.I)
_NAME = re.compile(r"[\w.+-]")
_SPELT_HOST = re.compile(r"[\w-]++(?:(?: ?[(\[]dot[)\]] ?|\.)[\w-]++)++|[\w-]++ ?\. ?[\w-]{2,}+", re.I)
_HOST = re.compile(r"[\w.-]{2,}+")


def _around(text: str, signs: Iterator[tuple[int, int]], host: re.Pattern) -> Iterator[tuple[int, int]]:
    """Names before and hosts behind signs; a name goes back to its start or to the sign before, so no character is read twice."""
    done = 0
    for a, b in signs:
        begin = a
        while begin > done and _NAME.match(text, begin - 1):
            begin -= 1
        done = b
        if begin < a and (m := host.match(text, b)):
            yield begin, m.start() + len(m.group().rstrip("."))


def _spelt(text: str) -> Iterator[tuple[int, int]]:
    return _around(text, (m.span() for m in _AT.finditer(text)), _SPELT_HOST)


def _signed(text: str) -> Iterator[tuple[int, int]]:
    return _around(text, (m.span() for m in re.finditer("@", text)), _HOST)


def _matches(pattern: str, flags: int = 0) -> Callable[[str], Iterator[tuple[int, int]]]:
    compiled = re.compile(pattern, flags)
    return lambda text: (m.span() for m in compiled.finditer(text))


#: Generators: a name, the kind that its spans get, and how they are found, in time linear in the text. All but ``number``,
#: which proposes parts of a run of numbers as ``digits`` and ``numbers`` propose whole ones, go on to the end of what they match.
GENERATORS = (
    ("number", "id", _matches(r"[+(]?[0-9][0-9 ().\-/:]{5,28}[0-9]")),
    ("spelt", "email", _spelt),
    ("sign", "email", _signed),
    ("keyed", "secret", _matches(r"(?<![A-Za-z])(?:password|passwd|passphrase|pwd|secret|token|credential|api[_-]?key|access[_-]?key|secret[_-]?key|private[_-]?key)[\"']? ?(?:=>|[=:]) ?(?:\"[^\"\n]{4,}+\"|'[^'\n]{4,}+'|[^\s,;]{6,}+)", re.I)),
    ("token", "secret", _matches(r"(?<![A-Za-z0-9_])[A-Za-z0-9_]{20,}+")),
    ("mixed", "id", _matches(r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,}+(?: ?[A-Z0-9]{1,3}(?![A-Za-z0-9]))?")),
    ("digits", "id", _matches(r"[+(]?[0-9](?:[().\-/:]{0,2}[0-9]){6,}+")),
    ("numbers", "id", _matches(r"[+(]?[0-9](?:[ ().\-/:]{0,3}[0-9]){6,}+")),
)
#: What a text has to have for each generator to find anything; cheap to look for.
_NEEDS = (
    _DIGIT,
    re.compile(r"[(\[]at[)\]]", re.I),
    re.compile(r"@"),
    re.compile(r"[=:]>? ?[^\s,;]{4}"),
    re.compile(r"[A-Za-z0-9_]{20}"),
    _DIGIT,
    _DIGIT,
    _DIGIT,
)
#: Words of the 28 characters before a candidate that tell what it is.
CONTEXT = (
    re.compile(r"phone|tel|call|mobile|fax|whatsapp|sms", re.I),
    re.compile(r"mail|contact|write to|reach", re.I),
    re.compile(r"card|visa|credit|account|iban|bank", re.I),
    re.compile(r"ssn|social|passport|licen[cs]e|tax|id\b|identity", re.I),
    re.compile(r"password|secret|token|key|credential|bearer", re.I),
    re.compile(r"version|isbn|page|fig|table|chapter|date|year|since|between|order|ticket|doi|rev|commit|\$|€|£|#", re.I),
)
N_FEATURES = len(GENERATORS) + len(CONTEXT) + 19


def candidates(text: str) -> list[tuple[int, int, int]]:
    """Overlapping ``(start, end, generator)`` proposals."""
    return [(a, b, k) for k, (_, _, find) in enumerate(GENERATORS) if _NEEDS[k].search(text) for a, b in find(text)]


def features(text: str, start: int, end: int, generator: int) -> list[float]:
    span, before, after = text[start:end], text[max(0, start - 28) : start], text[end : end + 2]
    n = end - start
    digits = "".join(_DIGIT.findall(span))
    letters = sum(map(str.isalpha, span))
    groups = re.findall(r"[0-9]+", span)
    return [
        *(float(k == generator) for k in range(len(GENERATORS))),
        *(float(c.search(before) is not None) for c in CONTEXT),
        n, len(digits), letters, len(digits) / n, letters / n, sum(map(str.isupper, span)), len(set(span)) / n, n - len(digits) - letters,
        len(groups), max(map(len, groups), default=0), min(map(len, groups), default=0), float(span[0] == "+"), float("@" in span), float(span.count(".")), float(span.count("-")), float(span.count("/") + span.count(":")),
        float(13 <= len(digits) <= 19 and luhn(digits)), float(before[-1:].isalnum()), float(after[:1].isalnum()),
    ]


class BoostedTrees:
    """Logistic gradient boosting over histograms; trees are grown by level to a fixed depth."""

    def __init__(self, trees: int = 40, depth: int = 4, rate: float = 0.3, bins: int = 32, ridge: float = 1.0) -> None:
        self.trees, self.depth, self.rate, self.bins, self.ridge = trees, depth, rate, bins, ridge
        self.nodes: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        self.cuts = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins)[1:-1])) for c in x.T]
        binned = np.column_stack([np.searchsorted(cut, c, side="left") for cut, c in zip(self.cuts, x.T)])
        self.start = float(np.log(y.mean() / (1 - y.mean())))
        margin, width, n_leaves = np.full(len(y), self.start), self.bins + 1, 1 << self.depth
        for _ in range(self.trees):
            p = 1 / (1 + np.exp(-margin))
            g, h = y - p, p * (1 - p)
            feature, cut, leaf = np.zeros(n_leaves, int), np.full(n_leaves, np.inf), np.ones(len(y), int)
            for level in range(self.depth):
                size = 2 << level
                gain = np.full((x.shape[1], size, width), -np.inf)
                for f in range(x.shape[1]):
                    cell = leaf * width + binned[:, f]
                    gl = np.cumsum(np.bincount(cell, g, size * width).reshape(size, width), 1)
                    hl = np.cumsum(np.bincount(cell, h, size * width).reshape(size, width), 1)
                    gr, hr = gl[:, -1:] - gl, hl[:, -1:] - hl
                    ok = (hl > 0.5) & (hr > 0.5)
                    gain[f][ok] = (gl**2 / (hl + self.ridge) + gr**2 / (hr + self.ridge))[ok]
                best = gain.transpose(1, 0, 2).reshape(size, -1)
                pick = best.argmax(1)
                for node in range(size // 2, size):
                    f, b = divmod(int(pick[node]), width)
                    if np.isfinite(best[node, pick[node]]) and b < len(self.cuts[f]):
                        feature[node], cut[node] = f, self.cuts[f][b]
                leaf = 2 * leaf + (x[np.arange(len(x)), feature[leaf]] > cut[leaf])
            at = leaf - n_leaves
            value = self.rate * np.bincount(at, g, n_leaves) / (np.bincount(at, h, n_leaves) + self.ridge)
            self.nodes.append((feature, cut, value))
            margin += value[at]
        return self

    def margin(self, x: np.ndarray) -> np.ndarray:
        out, row = np.full(len(x), self.start), np.arange(len(x))
        for feature, cut, value in self.nodes:
            leaf = np.ones(len(x), int)
            for _ in range(self.depth):
                leaf = 2 * leaf + (x[row, feature[leaf]] > cut[leaf])
            out += value[leaf - len(value)]
        return out


def _card_number(rng: random.Random) -> str:
    head = "".join(str(rng.randrange(10)) for _ in range(15))
    digits = next(head + str(k) for k in range(10) if luhn(head + str(k)))
    return rng.choice(["", " ", "-"]).join(digits[k : k + 4] for k in range(0, 16, 4))


def examples(n: int, seed: int) -> Iterator[tuple[str, int, int]]:
    """Texts with one planted item: ``(text, start, end)``; start = end where it is a look-alike only."""
    rng = random.Random(seed)
    num = lambda k: "".join(str(rng.randrange(10)) for _ in range(k))
    word = lambda: "".join(rng.choice("abcdefghiklmnoprstuvw") for _ in range(rng.randrange(2, 9)))
    hexa = lambda k: "".join(rng.choice("0123456789abcdef") for _ in range(k))
    personal = (
        (("call ", "phone: ", "tel. ", "mobile ", "my fax is "), lambda: rng.choice([f"({num(3)}) {num(3)}-{num(4)}", f"{num(3)}-{num(3)}-{num(4)}", f"+{num(2)} {num(3)} {num(3)} {num(3)}", f"0{num(2)} {num(4)} {num(4)}", f"{num(3)}.{num(3)}.{num(4)}"])),
        (("mail ", "contact ", "write to ", ""), lambda: rng.choice([str, str, str.upper])(rng.choice([f"{word()} (at) {word()} (dot) com", f"{word()}[at]{word()}.org", f"{word()}.{word()}@{word()}.net"]))),
        (("card ", "credit card: ", "visa ", "account "), lambda: _card_number(rng)),
        (("ssn ", "social security ", "tax id "), lambda: f"{num(3)}-{num(2)}-{num(4)}"),
        (("iban ", "bank account ", ""), lambda: f"DE{num(2)} {num(4)} {num(4)} {num(4)} {num(4)} {num(2)}"),
        (("", "the ", "set "), lambda: f"{rng.choice(['password', 'token', 'secret', 'api_key'])}{rng.choice(['=', ': '])}{rng.choice([hexa(18), hexa(32), hexa(rng.randrange(60, 1200)), word() + num(4) + '!' + word(), word() + word() + word() + rng.choice('!?#') * rng.randrange(2)])}"),
        (("key ", "token ", "bearer "), lambda: rng.choice([hexa(rng.choice([24, 32, 40])), hexa(rng.randrange(24, 1200)), "".join(rng.choice("abcdef") for _ in range(rng.randrange(24, 40)))])),
    )
    harmless = (
        (("on ", "date ", "since ", ""), lambda: f"{rng.choice(['19', '20'])}{num(2)}-0{rng.randrange(1, 10)}-{rng.randrange(10, 29)}"),
        (("at ", ""), lambda: f"{rng.randrange(10, 24)}:{rng.randrange(10, 60)}:{rng.randrange(10, 60)}"),
        (("version ", "rev ", ""), lambda: f"{num(1)}.{num(2)}.{num(2)}.{num(3)}-{num(2)}"),
        (("$", "price ", "sum of "), lambda: f"{num(1)}.{num(3)}.{num(3)},{num(2)}".replace(",", ".")),
        (("between ", "pages ", "years "), lambda: f"{num(4)}-{num(4)}"),
        (("isbn ", "ISBN: "), lambda: f"978-{num(1)}-{num(3)}-{num(5)}-{num(1)}"),
        (("order ", "ticket #", "fig. ", "table "), lambda: num(rng.randrange(7, 12))),
        (("", "the sum ", "about "), lambda: f"{num(3)} {num(3)} {num(3)}"),
        (("", "say ", "very "), lambda: "".join(word() for _ in range(6))[: rng.randrange(20, 40)]),
        (("about ", "chapter "), lambda: f"{num(1)} / {num(2)} / {num(4)}"),
        (("commit ", "rev "), lambda: hexa(40)),
    )
    for _ in range(n):
        good = rng.random() < 0.5
        before, make = rng.choice(personal if good else harmless)
        lead = " ".join(word() for _ in range(rng.randrange(0, 6)))
        if rng.random() < 0.3:  # a cue that belongs to something else
            lead = f"{lead} {rng.choice(rng.choice(personal + harmless)[0])}{word()}{rng.choice([' ', ', ', '. '])}{word()}"
        cue, item = rng.choice(before), make()
        head = f"{lead} {cue}"
        yield f"{head}{item}{rng.choice(['.', ' ', ', '])}{word()} {word()}", len(head), len(head) + len(item) if good else len(head)


def _labelled(n: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    x, y = [], []
    for text, start, end in examples(n, seed):
        for a, b, k in candidates(text):
            shared = min(b, end) - max(a, start)
            x.append(features(text, a, b, k))
            y.append(float(shared >= 0.7 * (b - a) and shared >= 0.7 * (end - start)))
    return np.array(x), np.array(y)


@dataclass(frozen=True)
class Detector:
    """Trees, the line that calibrates their margins, and the probability that a redaction of each kind needs."""

    trees: BoostedTrees
    slope: float
    shift: float
    thresholds: dict[str, float]

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.slope * self.trees.margin(x) + self.shift)))

    def added_spans(self, text: str | None, base: list[Span]) -> list[Span]:
        """Redactions beside ``base``: the most probable candidates, none overlapping another."""
        if not text:
            return []
        found = candidates(text)
        if not found:
            return []
        p = self.probabilities(np.array([features(text, *c) for c in found]))
        chosen = Intervals((a, b) for a, b, _ in base)
        wanted = sorted((-q, c) for q, c in zip(p, found) if q >= self.thresholds[GENERATORS[c[2]][1]])
        return [(a, b, GENERATORS[k][1]) for _, (a, b, k) in wanted if chosen.add(a, b)]


class Intervals:
    """Intervals without overlap, in order, so that a new one is looked up by bisection."""

    def __init__(self, given: Iterable[tuple[int, int]]) -> None:
        self.starts: list[int] = []
        self.ends: list[int] = []
        for a, b in sorted(given):
            if self.ends and a < self.ends[-1]:
                self.ends[-1] = max(b, self.ends[-1])
            else:
                self.starts.append(a)
                self.ends.append(b)

    def add(self, a: int, b: int) -> bool:
        """Take an interval in, unless it overlaps one that is there."""
        at = bisect_left(self.starts, a)
        if at < len(self.starts) and self.starts[at] < b or at and self.ends[at - 1] > a:
            return False
        self.starts.insert(at, a)
        self.ends.insert(at, b)
        return True


@cache
def detector(n: int = 4000, seed: int = 11, precision: float = 0.995) -> Detector:
    """Train on ``n`` generated examples, calibrate and set a threshold per kind on as many others.

    A kind's threshold is the lowest probability, 0.5 or more, down to which its candidates are right
    in a share of ``precision``; a kind without such a probability is never added.
    """
    trees = BoostedTrees().fit(*_labelled(n, seed))
    x, y = _labelled(n, seed + 1)
    m = trees.margin(x)
    a, b = 1.0, 0.0
    for _ in range(30):  # Newton steps on the logistic loss of a * margin + b
        p = 1 / (1 + np.exp(-(a * m + b)))
        w = p * (1 - p) + 1e-6
        hess = np.array([[(w * m * m).sum() + 1, (w * m).sum()], [(w * m).sum(), w.sum() + 1e-3]])
        step = np.linalg.solve(hess, [((y - p) * m).sum() - (a - 1), (y - p).sum()])
        a, b = a + step[0], b + step[1]
    p = 1 / (1 + np.exp(-(a * m + b)))
    thresholds = {}
    for kind in dict.fromkeys(g[1] for g in GENERATORS):
        mine = np.flatnonzero(x[:, [k for k, g in enumerate(GENERATORS) if g[1] == kind]].any(1))
        order = mine[np.argsort(-p[mine], kind="stable")]
        good = np.flatnonzero(np.cumsum(y[order]) / np.arange(1, len(order) + 1) >= precision)
        thresholds[kind] = float(max(0.5, p[order[good[-1]]])) if len(good) else 1.1
    return Detector(trees, a, b, thresholds)


def find_spans(text: str | None, model: Detector) -> tuple[list[Span], list[Span]]:
    """``(base, all)`` spans by start and kind."""
    base = base_spans(text)
    return base, sorted(base + model.added_spans(text, base), key=lambda s: (s[0], KINDS.index(s[2])))


def redact(text: str, spans: list[Span]) -> str:
    """The text with every span, or run of overlapping spans, as ``[KIND]``."""
    out, done = [], 0
    for start, end, kind in spans:
        if start >= done:
            out += [text[done:start], f"[{kind.upper()}]"]
        done = max(done, end)
    return "".join(out) + text[done:]


_SPANS = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))


def _scan(batches: Iterator[pa.RecordBatch], model: Detector, texts: bool) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 1000):
            part = batch.slice(at, 1000)
            base, every, clean = [], [], []
            for value in part.column("text"):
                text = value.as_py()
                b, e = find_spans(text, model)
                base.append([{"kind": k, "start": s, "end": t} for s, t, k in b])
                every.append([{"kind": k, "start": s, "end": t} for s, t, k in e])
                if texts:
                    clean.append(None if text is None else redact(text, e))
            cols = [part.column("doc_id"), pa.array(base, _SPANS), pa.array(every, _SPANS)] + [pa.array(clean, pa.string())] * texts
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "base", "spans"] + ["redacted"] * texts)


def find_personal_data(docs: DataFrame, texts: bool = True) -> DataFrame:
    """``doc_id, base, spans[, redacted]``; spans are arrays of (kind, start, end)."""
    model = detector()
    kind = docs.schema["doc_id"].dataType.simpleString()
    spans = "array<struct<kind: string, start: long, end: long>>"
    return docs.select("doc_id", "text").mapInArrow(lambda it: _scan(it, model, texts), f"doc_id {kind}, base {spans}, spans {spans}" + ", redacted string" * texts)


def digest(spans: list[Span]) -> str:
    """The hash of kind:start:end, comma-joined."""
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, b, k in spans).encode()).hexdigest()
