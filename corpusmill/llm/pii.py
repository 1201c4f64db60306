"""Personal data: fixed patterns, and a semi-Markov conditional random field over whole candidate spans.

The field scores each segment (a run of tokens with a type) by features of the whole span: its runs of digits, separators and letters, the words before and
after it, and how it touches them. Dynamic programming with a bounded segment length picks boundaries and types together. Weights are fitted on
sentences that `training_sentences` makes from templates (their number is a parameter); almost half of their values are look-alikes that are no
personal data. Decoding runs over the whole text: `decode` is the plain reading, and `crf_spans` gives the same spans from the segments that can be an entity
(every other one has no score) and of those from the ones with a score above 0 (no other one can win).
Defined results: null text is empty; rows are handled one by one (repeated ids repeat); extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
import string
from bisect import bisect_left, bisect_right
from collections import defaultdict
from functools import cache

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_columns, render_spans

#: The contract's patterns and order of kinds.
EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
BASE = ("email", "ip", "card", "phone")
TYPES = ("email", "phone", "iban", "ssn", "name", "birth", "passport")
KINDS = (*BASE, *(f"crf_{k}" for k in TYPES))
ORDER = {k: i for i, k in enumerate(KINDS)}

MAX_TOKENS = 14
#: The longest span in characters, and the fewest digits of one that is found by them.
LONGEST, DIGITS = 60, 5
#: Sentences that the field is fitted on.
SENTENCES = 500
_TOKEN = re.compile(r"[A-Za-z0-9]+|[^\sA-Za-z0-9]")
_DIGIT = re.compile(r"[0-9@]")
#: Small words inside names.
PARTICLES = ("van", "de", "von", "da", "der")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = ord(d) - 48
        if i % 2:
            n = n * 2 - 9 * (n > 4)
        total += n
    return total % 10 == 0


_OTHER = re.compile("[^0-9]+")


def _digits(s: str) -> str:
    return _OTHER.sub("", s)


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """Per kind leftmost non-overlapping matches; failing ones are dropped without a second try."""
    out: list[tuple[int, int, str]] = []
    if "@" in text:
        out += [(s, e, "email") for s, e in _emails(text)]
    if _DIGIT.search(text):
        if "." in text:
            out += [(*m.span(), "ip") for m in IP.finditer(text) if all(int(x[-4:]) <= 255 and len(x.lstrip("0")) <= 3 for x in m[0].split("."))]
        for m in CARD.finditer(text):
            if 14 <= len(d := _digits(m[0])) <= 19 and luhn(d):
                out.append((*m.span(), "card"))
        if "+" in text:
            out += [(*m.span(), "phone") for m in PHONE.finditer(text) if 10 <= len(_digits(m[0])) <= 15]
    return out


_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL_SET = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def _emails(text: str) -> list[tuple[int, int]]:
    """Matches of EMAIL, found from each at sign so that long runs without one cost nothing."""
    out: list[tuple[int, int]] = []
    free, at = 0, text.find("@")
    while at >= 0:
        m = _DOMAIN.match(text, at)
        start = at
        while start > free and text[start - 1] in _LOCAL_SET:
            start -= 1
        if m and start < at:
            out.append((start, m.end()))
            free = m.end()
        at = text.find("@", max(free, at + 1))
    return out


_AT = re.compile(r"@|[(\[] ?at ?[)\]]|(?<![a-z])at(?![a-z])", re.I)
_DOT = re.compile(r"[(\[] ?dot ?[)\]]|(?<![a-z])dot(?![a-z])|(?<=[a-z0-9])\.(?=[a-z])", re.I)
_WORDS = re.compile(r"[A-Z][a-z'-]+|[A-Z]\b")
_MONTH = re.compile(r"\b(?:jan|feb|mar|apr|may|jun|jul|aug|sep|oct|nov|dec)[a-z]*\b", re.I)


def _near(tokens: list[tuple[int, int]], text: str, at: int, step: int) -> list[str]:
    """The two nearest words beside a place, marks skipped."""
    out: list[str] = []
    while 0 <= at < len(tokens) and len(out) < 2:
        word = text[tokens[at][0] : tokens[at][1]].lower()
        if word.isalpha():
            out.append(word)
        elif word.isdigit():
            out.append("9")
        at += step
    return out + ["^"] * (2 - len(out))


def features(tokens: list[tuple[int, int]], text: str, i: int, j: int) -> list[str]:
    """Features of the whole span of tokens i..j-1."""
    before, beyond = _near(tokens, text, i - 1, -1)
    return span_features(text, tokens[i][0], tokens[j - 1][1], j - i, before, beyond, _near(tokens, text, j, 1)[0])


_RUNS, _LETTERS = re.compile("[0-9]+"), re.compile("[A-Za-z]+")
_CASES = {ord(c): "A" if c.isupper() else "a" for c in string.ascii_letters}
#: What introduces a name.
_SAID = re.compile(r"\b(?:[Mm]y name is|[Nn]ame:|[Mm]r\.?|[Mm]rs\.?|[Mm]s\.?|[Dd]r\.?|[Dd]ear|[Ss]igned,?|[Rr]egards,|am called)\s+\Z")
_SAYING = frozenset("is name mr mrs ms dr dear signed regards called".split())


def _said(text: str, start: int, before: str) -> bool:
    return before in _SAYING and _SAID.search(text, max(0, start - LONGEST), start) is not None


def _edges(text: str, start: int, end: int) -> tuple[bool, bool]:
    """Whether a span touches what is beside it."""
    left = start > 0 and not text[start - 1].isspace() and text[start - 1] not in "(\"':#="
    return left, end < len(text) and not text[end].isspace() and text[end] not in ".,;:!?)\"'"


def span_features(text: str, start: int, end: int, count: int, before: str, beyond: str, after: str) -> list[str]:
    """Features of a span of `count` tokens, with the words beside it."""
    span = text[start:end]
    n = len(_digits(span))
    letters = any(map(str.isalpha, span))
    runs = "-".join(str(min(len(r), 6)) for r in _RUNS.findall(span)[:6])
    seps = "".join(sorted({c for c in span if not c.isalnum()}))[:5]
    caps = "".join(w[:2].translate(_CASES) for w in _LETTERS.findall(span)[:5])
    edge_l, edge_r = _edges(text, start, end)
    mail = f"at={len(_AT.findall(span))}dot={min(len(_DOT.findall(span)), 3)}"
    head = "d" if span[0].isdigit() else "A" if span[0].isupper() else "a" if span[0].isalpha() else span[0]
    kind = "num" if not letters else "mix" if n else "word"
    return [
        f"n={min(n, 20)}", f"runs={runs}", f"seps={seps}", f"head={head}", f"kind={kind}", f"len={kind}{min(count, 12)}", f"caps={caps}", mail, f"{mail}{n > 0}",
        f"cue={kind}{before}", f"cue2={kind}{beyond}", f"cues={before}|{beyond}|{runs}", f"cuen={before}|{min(n, 20)}", f"next={kind}{after}", f"glued={edge_l}{edge_r}", f"said={kind}{_said(text, start, before)}", f"runs|seps={runs}|{seps}", f"head|n={head}{n}", f"month={bool(_MONTH.search(span))}",
    ]


def _plausible(span: str) -> bool:
    """Whether a span could be an entity at all: enough digits, an address in marks or words, or capitalised words."""
    n = len(_digits(span))
    if n >= 7 or n == 6 and (_MONTH.search(span) or re.search(r"[/.-]", span)) or "@" in span:
        return len(span) >= 6
    if n == 5 and _MONTH.search(span):
        return True
    if len(span) >= 8 and _AT.search(span) and _DOT.search(span):
        return True
    return not n and all(_WORDS.fullmatch(w) or w in PARTICLES for w in span.replace(".", "").split())


def _segments(tokens: list[tuple[int, int]], text: str) -> dict[int, list[tuple[int, list[str]]]]:
    """Candidate entity segments by end: at most MAX_TOKENS tokens without a line break, that could be one."""
    out: dict[int, list[tuple[int, list[str]]]] = defaultdict(list)
    for j in range(1, len(tokens) + 1):
        for i in range(max(0, j - MAX_TOKENS), j):
            span = text[tokens[i][0] : tokens[j - 1][1]]
            if "\n" in span or len(span) < 2 or len(span) > LONGEST or not (span[0].isalnum() or span[0] in "+(") or not span[-1].isalnum():
                continue
            if _plausible(span):
                out[j].append((i, features(tokens, text, i, j)))
    return out


def _score(weights: dict[tuple[str, str], float], kind: str, feats: list[str]) -> float:
    return sum(weights.get((kind, f), 0.0) for f in feats) + weights.get((kind, "bias"), 0.0)


def _logsum(xs: list[float]) -> float:
    top = max(xs)
    return top + math.log(sum(math.exp(x - top) for x in xs))


#: What the made sentences are put together from.
FIRST = "John Mary Anna Peter Paul Laura James Olga Ivan Sofia Marco Elena Thomas Julia David Sarah Ahmed Mei Carlos Ines".split()
LAST = "Smith Miller Meyer Garcia Rossi Dubois Novak Kim Brown Fischer Lopez Moreau Jensen Silva Weber Costa O'Neil Khan".split()
CUES = {
    "email": ["mail", "email", "write to", "contact", "reach me at", "address:", "send it to"], "phone": ["call", "tel:", "phone", "phone:", "ring me on", "mobile", "fax", "telephone number is"], "iban": ["IBAN", "account", "iban:", "pay to"],
    "ssn": ["SSN:", "ssn", "social security", "SSN", "social security number is"], "name": ["my name is", "Name:", "Mr.", "Mrs.", "Dr.", "Dear", "signed,", "regards,", "I am called", "Mr", "Ms"], "birth": ["born", "born on", "date of birth:", "DOB", "birthday is", "birth date"],
    "passport": ["passport", "passport no.", "passport number", "passport:"],
}
OTHER_CUES = "order item number invoice part serial version build ref ticket code page room on since until in at from total price measured about isbn sku id line chapter".split()


def training_sentences(count: int, seed: int = 7) -> list[tuple[str, list[tuple[int, int, str]]]]:
    """Sentences with known spans, made from templates; almost half of the values are numbers, dates and words that are no personal data."""
    rng = random.Random(seed)
    pick = rng.choice
    digits = lambda n: "".join(pick("0123456789") for _ in range(n))
    word = lambda: pick(["the", "a", "of", "to", "and", "is", "it", "was", "for", "".join(pick("abcdefghilmnoprstu") for _ in range(rng.randint(3, 8)))])
    some = lambda: "".join(pick("abcdefghilmnoprstu") for _ in range(rng.randint(3, 8)))
    months = "January February March April May June July August September October November December Jan Mar Sep".split()

    def phone() -> str:
        gap = pick("- . ".split(".")[0] + ". ")
        return pick([f"({digits(3)}) {digits(3)}-{digits(4)}", f"{digits(3)}{gap}{digits(3)}{gap}{digits(4)}", f"({digits(3)}) {digits(3)} {digits(4)}", f"0{digits(3)} {digits(7)}", f"0{digits(2)} {digits(4)} {digits(4)}", f"0{digits(3)}/{digits(6)}", f"0{digits(1)} {digits(2)} {digits(2)} {digits(2)} {digits(2)}", f"0{digits(9)}"])

    def birth() -> str:
        d, m, y = rng.randint(1, 28), rng.randint(1, 12), rng.randint(1930, 2009)
        return pick([f"{d:02}/{m:02}/{y}", f"{d}.{m}.{y}", f"{y}-{m:02}-{d:02}", f"{d} {pick(months)} {y}", f"{pick(months)} {d}, {y}"])

    def mail() -> str:
        user = pick([some(), f"{some()}.{some()}", f"{some()} dot {some()}"])
        at, dot = pick([("(at)", "."), (" (at) ", " (dot) "), ("[at]", "."), (" [at] ", " [dot] "), (" at ", " dot "), (" AT ", "."), (" AT ", " DOT "), ("(at)", "(dot)")])
        return f"{user}{at}{some()}{dot}{pick(['com', 'org', 'net', 'de', 'fr', 'co.uk'])}"

    make = {
        "email": mail, "phone": phone, "birth": birth,
        "iban": lambda: pick([f"{pick(['DE', 'FR', 'ES', 'IT'])}{digits(2)}{digits(18)}", f"{pick(['DE', 'GB', 'NL'])}{digits(2)} {digits(4)} {digits(4)} {digits(4)} {digits(4)}", f"{pick(['GB', 'NL'])}{digits(2)} {pick(['ABNA', 'NWBK'])} {digits(4)} {digits(4)} {digits(2)}"]),
        "ssn": lambda: pick([f"{digits(3)}-{digits(2)}-{digits(4)}", f"{digits(3)} {digits(2)} {digits(4)}"]),
        "name": lambda: pick([f"{pick(FIRST)} {pick(LAST)}", f"{pick(FIRST)} {pick('ABCJMR')}. {pick(LAST)}", pick(LAST), f"{pick(FIRST)} van {pick(LAST)}"]),
        "passport": lambda: f"{pick('CXGKPAB')}{pick(['', pick('ABCDEF')])}{digits(rng.randint(6, 8))}",
    }
    plain = [
        lambda: digits(7), lambda: digits(16), lambda: digits(12), lambda: f"{digits(4)}-{digits(2)}-{digits(2)} {digits(2)}:{digits(2)}:{digits(2)}", lambda: f"{digits(3)},{digits(3)},{digits(3)}", lambda: f"{digits(1)}.{digits(8)}",
        lambda: f"{digits(2)}.{digits(3)}.{digits(1)}.{digits(2)}", lambda: f"v{digits(1)}.{digits(4)}.{digits(4)}", lambda: f"{digits(4)} {digits(4)}", lambda: f"{digits(8)}-{digits(4)}", lambda: f"a{digits(9)}b{digits(6)}", lambda: f"978-{digits(1)}-{digits(2)}-{digits(6)}-{digits(1)}",
        phone, birth, make["ssn"], make["passport"], lambda: f"{pick(FIRST)} {pick(['Street', 'University', 'Airport', 'River'])}", lambda: f"{some()} at {some()}", lambda: f"{some()} at {some()}.com", lambda: pick(FIRST),
    ]
    sure = ("email", "iban")  # what shows by itself; the others need a word before them
    out = []
    for _ in range(count):
        text, spans = " ".join(word() for _ in range(rng.randint(0, 4))), []
        for _ in range(rng.randint(1, 2)):
            if rng.random() < 0.45:
                text += f" {pick([*OTHER_CUES, some()])}{pick(['', '', ':', ' no.'])} {pick(plain)()}"
            else:
                kind = pick(TYPES)
                text += f" {pick(CUES[kind] if kind not in sure else [*CUES[kind], word()])} "
                value = make[kind]()
                spans.append((len(text), len(text) + len(value), kind))
                text += value
            text += pick(["", ".", ",", " " + word(), " " + some(), ". The " + some()])
        out.append((text, spans))
    return out


def prose_sentences(count: int, seed: int = 11) -> list[str]:
    """Sentences without personal data: what capital letters do in running text, in titles and in lists."""
    rng = random.Random(seed)
    pick = rng.choice
    some = lambda: "".join(pick("abcdefghiklmnoprstuvwz") for _ in range(rng.randint(1, 9)))
    common = "the a of to and is it was for in on that this at as with by from de van von da der name mail phone call".split()
    word = lambda: pick(common) if rng.random() < 0.4 else some()
    proper = lambda: pick([*FIRST, *LAST]) if rng.random() < 0.2 else word().capitalize()
    out = []
    for _ in range(count):
        text = ""
        for _ in range(rng.randint(1, 3)):
            kind = rng.random()
            if kind < 0.5:
                words = [word() for _ in range(rng.randint(2, 8))]
                words[0] = words[0].capitalize()
                if rng.random() < 0.5:
                    words[rng.randrange(len(words))] = proper()
            elif kind < 0.8:
                words = [proper() for _ in range(rng.randint(1, 6))]
            else:
                words = [proper()] * rng.randint(2, 8)
            text += pick(["", "\n", " ", "- ", "("]) * (not text or rng.random() < 0.3) + " ".join(words) + pick([". ", ".", ", ", ": ", "; ", "! ", "\n", " ", ") "])
        out.append(text)
    return out


@cache
def fitted(count: int = SENTENCES, epochs: int = 5, rate: float = 0.15) -> dict[tuple[str, str], float]:
    """Weights by stochastic gradient on the field's log likelihood over `count` made sentences and half as many of plain prose, in turn."""
    weights: dict[tuple[str, str], float] = defaultdict(float)
    sums: dict[tuple[str, str], float] = defaultdict(float)
    prepared = []
    made, plain = training_sentences(count), prose_sentences(count // 2)
    for text, spans in (x for k, both in enumerate(made) for x in (both, *((t, []) for t in plain[k // 2 : k // 2 + k % 2]))):
        tokens = [m.span() for m in _TOKEN.finditer(text)]
        starts, ends = {s: i for i, (s, _) in enumerate(tokens)}, {e: i + 1 for i, (_, e) in enumerate(tokens)}
        prepared.append((len(tokens), _segments(tokens, text), {(starts[s], ends[e], k) for s, e, k in spans if s in starts and e in ends}))
    steps = 0
    for _ in range(epochs):
        for n, segments, gold in prepared:
            scores = {(i, j, k): _score(weights, k, f) for j in segments for i, f in segments[j] for k in TYPES}
            ahead, behind = [0.0] * (n + 1), [0.0] * (n + 1)
            by_end, by_start = defaultdict(list), defaultdict(list)
            for (i, j, k), s in scores.items():
                by_end[j].append((i, s))
                by_start[i].append((j, s))
            for j in range(1, n + 1):
                ahead[j] = _logsum([ahead[j - 1], *(ahead[i] + s for i, s in by_end[j])])
            for i in range(n - 1, -1, -1):
                behind[i] = _logsum([behind[i + 1], *(behind[j] + s for j, s in by_start[i])])
            for j in segments:
                for i, feats in segments[j]:
                    for k in TYPES:
                        step = ((i, j, k) in gold) - math.exp(min(0.0, ahead[i] + scores[i, j, k] + behind[j] - ahead[n]))
                        if abs(step) > 1e-3:
                            for f in (*feats, "bias"):
                                weights[k, f] += rate * step
            steps += 1
        for key, w in weights.items():
            sums[key] += w
    return {key: w / epochs for key, w in sums.items()}


def decode(text: str, weights: dict[tuple[str, str], float]) -> list[tuple[int, int, str]]:
    """Best joint segmentation of one stretch."""
    tokens = [m.span() for m in _TOKEN.finditer(text)]
    segments = _segments(tokens, text)
    if not segments:
        return []
    best, back = [0.0] * (len(tokens) + 1), [None] * (len(tokens) + 1)
    for j in range(1, len(tokens) + 1):
        best[j] = best[j - 1]
        for i, feats in segments.get(j, ()):
            for k in TYPES:
                s = best[i] + _score(weights, k, feats)
                if s > best[j]:
                    best[j], back[j] = s, (i, k)
    out, j = [], len(tokens)
    while j:
        if back[j]:
            i, k = back[j]
            out.append((tokens[i][0], tokens[j - 1][1], k))
            j = i
        else:
            j -= 1
    return out[::-1]


#: Spans and words whose scores a task remembers.
REMEMBERED = 1 << 17
#: Characters before a span that are looked at first for the words before it.
REACH = 40
_AT_SIGNS, _DOT_SIGNS = re.compile(r"@|at", re.I), re.compile("d[Oo][Tt]|D[Oo][Tt]|\\.(?<=[A-Za-z0-9\u017f\u212a].)[A-Za-z\u017f\u212a]")
_ALNUM = re.compile(r"[A-Za-z0-9]+")
#: Where a span of capitalised words can begin; the second and third groups are there if no other word can follow in the span.
_HEADS = re.compile(r"[A-Zdv](?<![A-Za-z0-9].)(?:(?<=[A-Z])([A-Za-z0-9]*)(?:(?=\x20[abce-uw-z]|[,;:!?)])())?|(?:(?<=v)\.*[ao]\.*n|(?<=d)\.*[ea](?:\.*r)?)(?![A-Za-z0-9])(?:(?=\x20[abce-uw-z]|[,;:!?)])())?)")
_SIGN_WORDS = frozenset(a + b + c for a, b, c in (*(("A", t, "") for t in "tT"), *(("D", o, t) for o in "oO" for t in "tT")))
_PIECE = re.compile(r"[A-Za-z.'-]+")
#: What in a span of capitalised words can be a sign of an address.
_SIGN = re.compile(r"[AaDd.](?:(?<=[A-Za-z]\.)[A-Za-z]|(?:(?<=[-'.]a)|(?<=A)(?<![A-Za-z]A))[Tt](?![A-Za-z])|(?:(?<=[-'.]d)|(?<=D)(?<![A-Za-z]D))[Oo][Tt](?![A-Za-z]))")
_GAP = re.compile(r"\s+")
_SLACK = 1e-6


class Field:
    """Weights by feature, and remembered scores of spans of capitalised words and of what stands beside them."""

    def __init__(self, weights: dict[tuple[str, str], float]) -> None:
        rows: dict[str, list[float]] = defaultdict(lambda: [0.0] * len(TYPES))
        for (kind, feature), w in weights.items():
            rows[feature][TYPES.index(kind)] = w
        self.weights, self.bias = weights, rows.pop("bias", [0.0] * len(TYPES))
        self.rows = dict(rows)
        self.own: dict[tuple[str, int], list[float]] = {}
        self.beside: dict[tuple[str, str], list[float]] = {}
        self.none = [0.0] * len(TYPES)
        self.tops = {(head, sign): self._most(head, sign) for head in "Aa" for sign in (False, True)}
        self.hopeless: dict[tuple, bool] = {}
        for word in PARTICLES:  # alone
            follows, glued = ([max([0.0, *(r[k] for n, r in self.rows.items() if n.startswith(start))]) for k in range(len(TYPES))] for start in ("next=word", "glued="))
            self.tops[word, False] = [sum(x) for x in zip(self.near_own(word, 1), follows, glued)]
        self.passed: dict[tuple[str, str, str], bool] = {}

    def scores(self, feats: list[str]) -> list[float]:
        """As _score gives them, for all types."""
        rows = [r for f in feats if (r := self.rows.get(f))]
        return [sum(r[k] for r in rows) + b for k, b in enumerate(self.bias)]

    def _most(self, head: str, sign: bool) -> list[float]:
        """The most that any span of capitalised words scores without the words before it."""
        get = lambda name, k: self.rows.get(name, self.none)[k]
        named = lambda start: [n for n in self.rows if n.startswith(start)]
        seps, caps, after = {n[5:] for n in named("seps=")}, named("caps="), named("next=word")
        mails = [n for n in named("at=") if f"{n}False" in self.rows and n != "at=0dot=0"] if sign else []
        out = []
        for k, most in enumerate(self.bias):
            most += sum(get(n, k) for n in ("n=0", "runs=", "kind=word", f"head={head}", f"head|n={head}0"))
            most += max([0.0, *(get(f"seps={q}", k) for q in seps)]) + max([0.0, *(get(n, k) for n in named("runs|seps=|"))]) + max(get(f"len=word{c}", k) for c in range(1, 13))
            most += max([0.0, *(get(n, k) for n in caps)]) + max([0.0, *(get(n, k) for n in after)]) + max(get(f"month={b}", k) for b in (False, True)) + max(get(f"glued={a}{b}", k) for a in (False, True) for b in (False, True))
            none = get("at=0dot=0", k) + get("at=0dot=0False", k)
            out.append(most + (max([0.0, none, *(max(get(n, k), 0.0) + max(get(f"{n}False", k), 0.0) for n in mails)]) if sign else none))
        return out

    def no_name(self, head: str, sign: bool, near: tuple[str, str], said: bool) -> bool:
        """Whether no span of capitalised words that begins here has a score above 0."""
        key = (head, sign, near, said)
        if (held := self.hopeless.get(key)) is None:
            if len(self.hopeless) >= REMEMBERED:
                self.hopeless.clear()
            held = self.hopeless[key] = max(map(sum, zip(self.tops[head, sign], self.near_before(*near), self.rows.get(f"said=word{said}", self.none)))) < -_SLACK
        return held

    def near_own(self, span: str, count: int) -> list[float]:
        """Scores of a span without digits, up to what its neighbours add."""
        key = (span, count)
        if (held := self.own.get(key)) is None:
            feats = span_features(span, 0, len(span), count, "", "", "")
            held = self.scores([f for f in feats if not f.startswith(("cue", "next=", "glued=", "said="))])
            if len(self.own) >= REMEMBERED:
                self.own.clear()
            self.own[key] = held
        return held

    def near_before(self, before: str, beyond: str) -> list[float]:
        key = (before, beyond)
        if (held := self.beside.get(key)) is None:
            rows = [r for f in (f"cue=word{before}", f"cue2=word{beyond}", f"cues={before}|{beyond}|", f"cuen={before}|0") if (r := self.rows.get(f))]
            held = [sum(r[k] for r in rows) for k in range(len(TYPES))]
            if len(self.beside) >= REMEMBERED:
                self.beside.clear()
            self.beside[key] = held
        return held


_FIELDS: dict[int, Field] = {}


def _field(weights: dict[tuple[str, str], float]) -> Field:
    held = _FIELDS.get(id(weights))
    if held is None or held.weights is not weights:
        if len(_FIELDS) >= 4:
            _FIELDS.clear()
        held = _FIELDS[id(weights)] = Field(weights)
    return held


def _word(token: str) -> str | None:
    low = token.lower()
    return low if low.isalpha() else "9" if low.isdigit() else None


def _words_before(text: str, at: int) -> tuple[str, str]:
    """The two nearest words before a place, marks skipped."""
    reach = REACH
    while True:
        low = max(0, at - reach)
        tokens = _TOKEN.findall(text, low, at)
        whole = not low
        if not whole and tokens and _ALNUM.match(text, low) and _ALNUM.match(text, low - 1):
            tokens = tokens[1:]  # cut
        found = []
        for token in reversed(tokens):
            if word := _word(token):
                found.append(word)
                if len(found) == 2:
                    return found[0], found[1]
        if whole:
            found += ["^"] * (2 - len(found))
            return found[0], found[1]
        reach *= 4


def _word_after(text: str, at: int) -> str:
    for m in _TOKEN.finditer(text, at):
        if word := _word(m[0]):
            return word
    return "^"


def _numbered(text: str) -> list[list[int]]:
    """Merged stretches that hold every span with DIGITS digits, an at sign, or signs of an address in words."""
    out: list[tuple[int, int]] = []
    places = [m.start() for m in re.finditer("[0-9]", text)]
    for first, last in zip(places, places[DIGITS - 1 :]):
        if last - first < LONGEST:
            out.append((last - LONGEST + 1, first + LONGEST))
    at = text.find("@")
    while at >= 0:
        out.append((at - LONGEST + 1, at + LONGEST))
        at = text.find("@", at + 1)
    for m in _DOT_SIGNS.finditer(text):
        low, high = m.end() - LONGEST, m.start() + LONGEST
        if _AT_SIGNS.search(text, max(0, low), min(len(text), high)):
            out.append((low, high))
    merged: list[list[int]] = []
    for low, high in sorted(out):
        if merged and low <= merged[-1][1]:
            merged[-1][1] = max(high, merged[-1][1])
        else:
            merged.append([low, high])
    return merged


def _numbered_segments(text: str, field: Field, out: dict[tuple[int, int], list[float]]) -> None:
    """Scores of the segments of _segments that hold digits or signs of an address, by their ends; without a score above 0 they are left out."""
    for low, high in _numbered(text):
        low, high = max(0, low), min(len(text), high)
        tokens = [m.span() for m in _TOKEN.finditer(text, low, high)]
        if tokens and low and _ALNUM.match(text, low) and _ALNUM.match(text, low - 1):
            tokens = tokens[1:]
        if tokens and high < len(text) and tokens[-1][1] == high and _ALNUM.match(text, high - 1) and _ALNUM.match(text, high):
            tokens = tokens[:-1]
        digits = [0]
        for a, b in tokens:
            digits.append(digits[-1] + len(_digits(text[a:b])))
        words: dict[int, tuple[str, str]] = {}
        signed = _AT_SIGNS.search(text, low, high) is not None
        starts = [text[a].isalnum() or text[a] in "+(" for a, _ in tokens]
        for j in range(1, len(tokens) + 1):
            end = tokens[j - 1][1]
            if not text[end - 1].isalnum():
                continue
            after = None
            for i in range(j - 1, max(0, j - MAX_TOKENS) - 1, -1):
                start = tokens[i][0]
                if end - start > LONGEST:
                    break
                if not starts[i] or end - start < 2:
                    continue
                span = text[start:end]
                if "\n" in span:
                    break
                if digits[j] - digits[i] < DIGITS and not (signed and ("@" in span or _AT_SIGNS.search(span) and _DOT_SIGNS.search(span))) or not _plausible(span):
                    continue
                if after is None:
                    after = _word_after(text, end)
                if i not in words:
                    words[i] = _words_before(text, start)
                scores = field.scores(span_features(text, start, end, j - i, *words[i], after))
                if max(scores) > 0:
                    out[start, end] = scores


def _named_segments(text: str, field: Field, out: dict[tuple[int, int], list[float]]) -> None:
    """The same for segments of capitalised words without digits."""
    rows, none, passed, sign_at = field.rows, field.none, field.passed, -1
    for m in _HEADS.finditer(text):
        start = m.start()
        head = "A" if m[1] is not None else m[0] if m.lastindex == 3 and m[0] in PARTICLES else "a"
        if m.lastindex == 2:
            sign = m[0] in _SIGN_WORDS
        elif len(head) > 1:
            sign = False
        else:
            if sign_at < start:
                sign_at = found.start() if (found := _SIGN.search(text, start)) else len(text) + LONGEST
            sign = sign_at < start + LONGEST
        parts = text[max(0, start - REACH) : start].rsplit(None, 2)
        beside = (head, parts[1], parts[2]) if len(parts) == 3 and not sign else None
        if beside and passed.get(beside):
            continue
        near = _words_before(text, start)
        told = _said(text, start, near[0])
        if field.no_name(head, sign, near, told):
            if beside and near[0] not in _SAYING and sum(1 for t in _TOKEN.findall(" ".join(beside[1:])) if _word(t)) > 1:  # these two pieces decide
                if len(passed) >= REMEMBERED:
                    passed.clear()
                passed[beside] = True
            continue
        before, said = field.near_before(*near), rows.get(f"said=word{told}", none)
        at, whole = start, True
        while whole and at - start < LONGEST and (piece := _PIECE.match(text, at)):
            whole = False
            stop = piece.end()
            for run in _ALNUM.finditer(text, at, stop):
                end = run.end()
                if end - start > LONGEST or end < len(text) and _ALNUM.match(text, end):
                    break
                span = text[start:end]
                if len(span) < 2 or not _plausible(span):
                    continue
                count = len(_TOKEN.findall(span))
                if count > MAX_TOKENS:
                    break
                after = _word_after(text, end)
                edges = _edges(text, start, end)
                follows, glued = rows.get(f"next=word{after}", none), rows.get(f"glued={edges[0]}{edges[1]}", none)
                if max(map(sum, zip(field.near_own(span, count), before, said, follows, glued))) > -_SLACK:
                    scores = field.scores(span_features(text, start, end, count, *near, after))
                    if max(scores) > 0:
                        out[start, end] = scores
            if not (rest := text[at:stop].replace(".", "")) or _WORDS.fullmatch(rest) or rest in PARTICLES:
                gap = _GAP.match(text, stop)
                if gap and "\n" not in gap[0]:
                    whole, at = True, gap.end()


def crf_spans(text: str, weights: dict[tuple[str, str], float], taken: list[list[int]]) -> list[tuple[int, int, str]]:
    """The spans that `decode` gives for the whole text, without those that meet a taken span."""
    field = _field(weights)
    scored: dict[tuple[int, int], list[float]] = {}
    _numbered_segments(text, field, scored)
    _named_segments(text, field, scored)
    ends, bests, backs = [0], [0.0], [None]  # places where the best sum rises
    for start, end in sorted(scored, key=lambda x: (x[1], x[0])):
        base = bests[bisect_right(ends, start) - 1]
        for kind, score in zip(TYPES, scored[start, end]):
            if base + score > bests[-1]:
                if ends[-1] != end:
                    ends.append(end), bests.append(0.0), backs.append(None)
                bests[-1], backs[-1] = base + score, (start, kind)
    out, at = [], len(text)
    while back := backs[bisect_right(ends, at) - 1]:
        out.append((back[0], ends[bisect_right(ends, at) - 1], back[1]))
        at = back[0]
    return [(s, e, k) for s, e, k in out[::-1] if not (near := bisect_left(taken, [e])) or taken[near - 1][1] <= s]


def scan(text: str | None, weights: dict[tuple[str, str], float]) -> tuple:
    text = text or ""
    base = base_spans(text)
    spans = list(base)
    taken: list[list[int]] = []
    for s, e in sorted((s, e) for s, e, _ in base):
        if taken and s < taken[-1][1]:
            taken[-1][1] = max(e, taken[-1][1])
        else:
            taken.append([s, e])
    spans += [(s, e, f"crf_{kind}") for s, e, kind in crf_spans(text, weights, taken)]  # what a fixed pattern has keeps that pattern's kind
    counts = [sum(k == kind for _, _, k in base) for kind in BASE]
    return (*counts, hashlib.sha256(render_spans(base, ORDER).encode()).hexdigest(), render_spans(spans, ORDER))


def scan_pii(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sentences: int = SENTENCES) -> DataFrame:
    """One row per document: counts and digest of the base kinds, and all spans (code points, end exclusive)."""
    weights = fitted(sentences)
    names = ("n_email", "n_ip", "n_card", "n_phone")
    fields = [(id_col, pa.int64()), *((n, pa.int64()) for n in names), ("base_sha256", pa.string()), ("spans", pa.string())]
    schema = f"`{id_col}` long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"

    def kernel(ids: list, texts: list) -> list:
        return [ids, *zip(*(scan(t, weights) for t in texts))] if ids else [[] for _ in fields]

    return map_columns(docs, kernel, schema, pa.schema(fields), id_col, text_col)
