"""Personal data by candidate boosting.

Base spans come from four formats with exact rules (email, ip, card, phone) and always stand. Beyond
them, generators with high recall propose further spans, overlapping ones included: obfuscated
addresses, numbers grouped like phones, cards, social security numbers, IPv6 addresses, and secrets
(key=value credentials, access keys). Boosted trees score each candidate by its format (lengths,
character classes, checksum, groups, entropy) and context (cue words and characters around it); a
threshold per kind, calibrated for precision on candidates not trained on, selects; of overlapping
ones the best-scored stays, and none may touch a base span.

The trees are trained here on generated candidates with fixed seed: formats filled with random
values, with and without cues, against look-alikes (dates, versions, prices, measures, identifiers).

All work is per document; offsets are code points, ends exclusive. Runs of any length take linear
time. Cases: null and empty texts have no spans; null ids, repeated rows and further columns stay as
they are; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from dataclasses import dataclass, field
from functools import lru_cache
from math import log2

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from tidegraph.llm.boosting import BoostedTrees
from tidegraph.llm.common import per_batch
from tidegraph.llm.textblocks import blocks

#: Order of kinds in span lists: the base kinds, then those that only the method finds.
KINDS = ("email", "ip", "card", "phone", "ssn", "secret")
BASE_KINDS = KINDS[:4]

Span = tuple[str, int, int]

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(text: str) -> list[Span]:
    """The exact formats, leftmost and non-overlapping within a kind; a match that fails its rule is dropped."""
    out: list[Span] = []
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at) if start < at else None
        if m:
            out.append(("email", start, m.end()))
            done = m.end()
        else:
            done = max(done, at + 1)  # no later match can hold this sign
        at = text.find("@", done)
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split(".")):
            out.append(("ip", *m.span()))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 16:
            d = _digits(m.group())
            if 16 <= len(d) <= 19 and luhn(d):
                out.append(("card", *m.span()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 8 <= sum("0" <= c <= "9" for c in m.group()) <= 15:
                out.append(("phone", *m.span()))
    return out


#: What may stand for the signs of an address in obfuscated ones.
_AT = re.compile(r" ?[\[({<] ?(?:at|AT|At|@) ?[\])}>] ?")
_AFTER = re.compile(r"[A-Za-z0-9-]++(?: ?[\[({<]? ?(?:dot|DOT|Dot|\.) ?[\])}>]? ?[A-Za-z0-9-]++)+")
_NUMBER = re.compile(r"(?<![0-9A-Za-z])[(+]{0,2}[0-9](?:[ ().\-/]{0,2}[0-9]){6,24}(?![0-9A-Za-z])")
_HEXGROUPS = re.compile(r"(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{1,4}:){2,7}(?::?[0-9A-Fa-f]{1,4})+(?![0-9A-Za-z:])")
_ACCESS = re.compile(r"(?<![A-Za-z0-9])[A-Z]{4}[A-Z0-9]{16}(?![A-Za-z0-9])")
_VALUE = re.compile(r"""\s{0,2}["']?([A-Za-z0-9_/+.-]{8,}=*)""")
_KEY = re.compile(r"([A-Za-z_][A-Za-z_-]*)\s{0,2}$")

#: Cue words by kind.
CUES = {
    "email": ("mail", "contact", "write", "reach"),
    "ip": ("ip", "host", "server", "addr"),
    "card": ("card", "visa", "credit", "pay"),
    "phone": ("phone", "tel", "call", "mobile", "fax", "cell"),
    "ssn": ("ssn", "social", "security"),
    "secret": ("token", "password", "passwd", "pwd", "secret", "key", "auth", "credential"),
}


def candidates(text: str, low: str | None = None) -> list[Span]:
    """High recall: spans of different kinds may overlap."""
    out: list[Span] = []
    if any(b in text for b in "[({<"):
        done = 0
        for sign in _AT.finditer(text):
            start = sign.start()
            while start > done and text[start - 1] in _LOCAL:
                start -= 1
            if start < sign.start() and (m := _AFTER.match(text, sign.end())):
                out.append(("email", start, m.end()))
            done = sign.end()
    for m in _NUMBER.finditer(text):
        n = len(_digits(m.group()))
        if 7 <= n <= 15:
            out.append(("phone", *m.span()))
        if n == 9:
            out.append(("ssn", *m.span()))
        if 13 <= n <= 19:
            out.append(("card", *m.span()))
    if ":" in text:
        out += [("ip", *m.span()) for m in _HEXGROUPS.finditer(text)]
    out += [("secret", *m.span()) for m in _ACCESS.finditer(text)]
    for sign in "=:":
        at = text.find(sign)
        while at >= 0:
            if _KEY.search(text, max(0, at - 24), at) and (m := _VALUE.match(text, at + 1)):
                out.append(("secret", *m.span(1)))
            at = text.find(sign, at + 1)
    return out


def features(text: str, span: Span) -> list[float]:
    kind, a, b = span
    s = text[a:b]
    d = _digits(s)
    before, after = text[max(0, a - 28) : a].lower(), text[b : b + 20].lower()
    groups = re.split(r"[^0-9A-Za-z]+", s.strip("()+ "))
    counts = Counter(s)
    entropy = -sum(c / len(s) * log2(c / len(s)) for c in counts.values())
    cue = [float(any(w in before for w in CUES[k])) for k in KINDS]
    own = float(any(w in before or w in after for w in CUES[kind]))
    letters = sum(c.isalpha() for c in s)
    return [
        float(KINDS.index(kind)), own, *cue, float(len(s)), float(len(d)), float(letters), float(sum(c.isupper() for c in s)),
        len(d) / len(s), entropy, float(13 <= len(d) <= 19 and luhn(d)), float(len(groups)), float(len(groups[0])), float(len(groups[-1])),
        float(max(map(len, groups))), float(s.count("-")), float(s.count(".")), float(s.count(" ")), float(s.count("/")), float(s.count("(")), float(s.count(":")),
        float(s[0] in "(+"), float(before[-1:].isalnum() or before[-1:] in {"$", "#", "."}), float(after[:1] in {"%", "/", "."} and after[1:2].isalnum()),
        float(bool(re.search(r"[=:]\s*[\"']?$", before))), float(bool(re.match(r"(?:19|20)\d\d\D|\d{1,2}[./-]\d{1,2}[./-]", s))), float(bool(re.fullmatch(r"[0-9a-fA-F]+", s))),
    ]


def _training(seed: int, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Candidates of generated sentences: features, whether the candidate is exactly a planted span of its kind, kinds."""
    rng = np.random.default_rng(seed)
    pick = lambda xs: xs[int(rng.integers(len(xs)))]
    number = lambda k: "".join(str(int(x)) for x in rng.integers(0, 10, k))
    word = lambda: "".join(pick(("an", "er", "the", "on", "re", "ti", "lo", "ma", "es", "in")) for _ in range(int(rng.integers(1, 4))))
    token = lambda k, chars="abcdefghijklmnopqrstuvwxyz0123456789": "".join(pick(chars) for _ in range(k))

    def card(k: int) -> str:
        body = number(k - 1)
        return next(body + str(c) for c in range(10) if luhn(body + str(c)))

    def grouped(s: str, size: int, sep: str) -> str:
        return sep.join(s[i : i + size] for i in range(0, len(s), size))

    def real(kind: str) -> str:
        if kind == "email":
            at, dot = pick(((" [at] ", " [dot] "), (" (at) ", " (dot) "), ("[at]", "."), (" {at} ", "."), ("(at)", "(dot)"), ("<at>", ".")))
            return f"{word()}.{number(2)}{at}{word()}{dot}{pick(('com', 'org', 'net'))}"
        if kind == "ip":
            return ":".join(token(int(rng.integers(2, 5)), "0123456789abcdef") for _ in range(8))
        if kind == "card":
            return grouped(card(pick((13, 14, 15, 16))), 4, pick((".", "/", " ", "-")))
        if kind == "phone":
            return pick(("({}) {}-{}", "{}-{}-{}", "{}.{}.{}", "{} {} {}", "00{} {} {}")).format(number(3), number(3), number(4))
        if kind == "ssn":
            return f"{number(3)}-{number(2)}-{number(4)}"
        return pick((lambda: pick(("AKIA", "ASIA")) + token(16, "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"), lambda: token(int(rng.integers(16, 44)), "0123456789abcdef"), lambda: token(int(rng.integers(12, 40)))))()

    def fake() -> str:
        return pick((
            lambda: f"{int(rng.integers(1900, 2100))}-{number(2)}-{number(2)}", lambda: f"{number(2)}/{number(2)}/{number(4)}", lambda: f"{number(1)}.{number(1)}.{number(2)}.{number(4)}",
            lambda: f"{number(3)}.{number(3)}.{number(3)}", lambda: number(int(rng.integers(7, 20))), lambda: f"{number(4)} {number(4)}", lambda: f"isbn {number(3)}-{number(1)}-{number(5)}-{number(3)}-{number(1)}",
            lambda: f"{number(2)}:{number(2)}:{number(2)}", lambda: f"{word()}: {word()}{word()}{word()}{word()}", lambda: f"{word()}={word()}{word()}{word()}{word()}", lambda: f"https://{word()}.{word()}/{word()}{word()}",
            lambda: token(20, "ABCDEFGHIJKLMNOPQRSTUVWXYZ"), lambda: f"{number(4)}-{number(4)}", lambda: f"{word()} (at {word()}) {word()}.{word()}", lambda: f"${number(3)},{number(3)}.{number(2)}", lambda: f"version {number(2)}.{number(2)}.{number(4)}",
        ))()

    x, y, kinds = [], [], []
    for _ in range(n):
        kind = pick(KINDS)
        true = rng.random() < 0.5
        if true:
            value = real(kind)
            cue = f"{pick(CUES[kind])}{pick((' ', ': ', '=', ' = '))}" if rng.random() < 0.8 or kind == "phone" else ""
            if kind == "secret" and not value.startswith(("AKIA", "ASIA")):
                cue = f"{pick(CUES['secret'])}{pick(('=', ' = ', ': '))}" + pick(("", '"'))
        else:
            value = fake()
            cue = f"{pick(CUES[pick(KINDS[:5])])} " if rng.random() < 0.1 else ""
        lead = " ".join(word() for _ in range(int(rng.integers(0, 5))))
        lead += " " if lead else ""
        text = f"{lead}{cue}{value} {word()} {word()}"
        at = len(lead) + len(cue)
        for c in candidates(text):
            x.append(features(text, c))
            y.append(float(true and c == (kind, at, at + len(value))))
            kinds.append(KINDS.index(c[0]))
    return np.array(x), np.array(y), np.array(kinds)


@dataclass
class PersonalData:
    """The trained selector. precision: wanted of each kind's accepted candidates, on those kept back."""

    precision: float = 0.98
    rows: int = 6000
    seed: int = 17
    trees: BoostedTrees = field(default_factory=BoostedTrees)
    thresholds: np.ndarray = field(default_factory=lambda: np.full(len(KINDS), np.inf))

    def fit(self) -> PersonalData:
        x, y, _ = _training(self.seed, self.rows)
        self.trees.fit(x, y)
        x, y, kinds = _training(self.seed + 1, self.rows // 2)
        odds = self.trees.log_odds(x)
        for k in range(len(KINDS)):
            at = np.flatnonzero(kinds == k)
            at = at[np.argsort(-odds[at], kind="stable")]
            right = np.cumsum(y[at]) / np.arange(1, len(at) + 1)
            good = np.flatnonzero(right >= self.precision)
            # never below even odds
            self.thresholds[k] = max(0.0, odds[at[good[-1]]]) if len(good) else np.inf
        return self

    def spans(self, text: str) -> tuple[list[Span], list[Span]]:
        """Base spans, and all spans; each by kind as listed, then start."""
        base = base_spans(text)
        found = candidates(text)
        taken = sorted((a, b) for _, a, b in base)
        added: list[Span] = []
        if found:
            odds = self.trees.log_odds(np.array([features(text, c) for c in found]))
            edges = np.array([x for ab in merged(taken) for x in ab])
            for i in np.argsort(-odds, kind="stable"):
                kind, a, b = found[i]
                if odds[i] < self.thresholds[KINDS.index(kind)]:
                    continue
                # free if both ends fall into the same gap
                lo, hi = np.searchsorted(edges, a, side="right"), np.searchsorted(edges, b, side="left")
                if lo == hi and lo % 2 == 0:
                    added.append(found[i])
                    edges = np.insert(edges, lo, [a, b])
        order = lambda s: (KINDS.index(s[0]), s[1])
        return sorted(base, key=order), sorted([*base, *added], key=order)


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Ascending spans with overlaps joined."""
    out: list[tuple[int, int]] = []
    for a, b in spans:
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], b))
        else:
            out.append((a, b))
    return out


@lru_cache(maxsize=1)
def trained() -> PersonalData:
    return PersonalData().fit()


def as_text(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def redact(text: str, spans: list[Span]) -> str:
    """Each span, or run of overlapping ones, becomes the name of its first kind in brackets."""
    out, at = [], 0
    joined = merged(sorted((a, b) for _, a, b in spans))
    names = {a: k for k, a, _ in sorted(spans, key=lambda s: (-s[1], -s[2]))}
    for a, b in joined:
        out += [text[at:a], f"[{names[a].upper()}]"]
        at = b
    return "".join([*out, text[at:]])


_MAY = np.zeros(256, bool)
_MAY[48:58] = True
_MAY[[ord(c) for c in "@+=:"]] = True
_MAY[65:91] = False


def _texts(column: pa.Array):
    """Each text that may hold a span, else None: no digit, no sign of an address or assignment, no bracket, no twenty capitals."""
    for block in blocks(column):
        flags = _MAY[block.data] | (block.data == 91) | (block.data == 40) | (block.data == 123) | (block.data == 60)
        capitals = np.concatenate(([0], np.cumsum((block.data >= 65) & (block.data < 91))))
        flags[: max(len(flags) - 19, 0)] |= capitals[20:] - capitals[:-20] == 20  # where twenty of them start
        may = np.zeros(block.n, bool)
        some = np.flatnonzero(block.lengths)
        if len(some):
            may[some] = np.logical_or.reduceat(flags, block.offsets[:-1][some])
        raw = block.data.tobytes()
        for i in range(block.n):
            yield str(raw[block.offsets[i] : block.offsets[i + 1]], "utf-8", "replace") if may[i] else None


def find(docs: DataFrame, model: PersonalData, text_column: str = "text", output: str = "spans") -> DataFrame:
    """docs without the text, with n_<kind> of base spans, base_sha256 and spans; or, with output="text", docs
    with the text redacted and n_chars, if there, counted anew."""
    names, at = docs.columns, docs.columns.index(text_column)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    if output == "text":
        chars = names.index("n_chars") if "n_chars" in names else None

        def clean(batch: pa.RecordBatch) -> pa.RecordBatch:
            columns = list(batch.columns)
            old = batch.column(at)
            new = []
            for text, was in zip(_texts(old), old, strict=True):
                spans = shared.value.spans(text)[1] if text else []
                new.append(redact(text, spans) if spans else was.as_py())
            columns[at] = pa.array(new, old.type)
            if chars is not None:
                columns[chars] = pa.array([None if t is None else len(t) for t in new], columns[chars].type)
            return pa.RecordBatch.from_arrays(columns, names=names)

        return per_batch(docs, clean, docs.schema, cut=True)

    added = [*(f"n_{k}" for k in BASE_KINDS), "base_sha256", "spans"]
    kept = [i for i, x in enumerate(names) if i != at and x not in added]

    def one(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows: list[list] = [[] for _ in added]
        empty = hashlib.sha256(b"").hexdigest()
        for text in _texts(batch.column(at)):
            base, every = shared.value.spans(text) if text else ([], [])
            count = Counter(k for k, _, _ in base)
            values = [*(count[k] for k in BASE_KINDS), hashlib.sha256(as_text(base).encode()).hexdigest() if base else empty, as_text(every)]
            for r, v in zip(rows, values, strict=True):
                r.append(v)
        out = [pa.array(r, pa.int64()) for r in rows[:4]] + [pa.array(r, pa.string()) for r in rows[4:]]
        return pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), *out], names=[*(names[i] for i in kept), *added])

    schema = T.StructType([docs.schema.fields[i] for i in kept])
    for name in added[:4]:
        schema = schema.add(name, "long")
    return per_batch(docs, one, schema.add("base_sha256", "string").add("spans", "string"))
