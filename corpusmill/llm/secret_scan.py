"""Secret scans: kinds found in the text itself, then in every layer that decoding it uncovers.

A worklist holds layers; each is scanned, and what it hides becomes new layers until none is new. URL escapes, Unicode escapes and base64 runs
are decoded in place, so that a match may join plain and decoded characters, and each character of a layer knows the characters of the text that it
came from; a match counts if it holds a decoded character. Base64 that is wrapped over lines and the windows of compressed bodies are layers of their own, whose
matches have the span of the encoded run. Compressed bodies unfold window by window, so a worker holds one window a depth however large the body is.
Defined results: null text is empty; rows are handled one by one (repeated ids repeat); bytes that are not UTF-8 and lone surrogates are read as
replacement characters; extra columns are ignored.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import unquote_to_bytes

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_columns, render_spans

#: The contract's patterns, least lengths and order of kinds.
ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "private_key", "bearer", "hidden_assign", "hidden_access", "hidden_hex", "hidden_private_key", "hidden_bearer")
ORDER = {k: i for i, k in enumerate(KINDS)}
BASE = ("assign", "access", "hex")

_KEY = re.compile(r"-----BEGIN (?:[A-Z]+ )?PRIVATE KEY-----")
_BEARER = re.compile(r"[Bb]earer\x20+(?=[A-Za-z0-9_-]*[0-9])[A-Za-z0-9_-]{12,}(?:\.[A-Za-z0-9_-]+)*")
_BASE64 = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{16,}={0,2}")
_WRAPPED = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]++(?:[\x20\t]*+\r?\n[\x20\t]*+[A-Za-z0-9+/_-]++)+={0,2}")
_LINE_RUN = re.compile(r"[A-Za-z0-9+/_-]+")
_RUN = re.compile(r"\S+")
_PERCENT = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
_ESCAPE = re.compile(r"\\(?:u([0-9A-Fa-f]{4})|x([0-9A-Fa-f]{2}))")
_ESCAPES = re.compile(r"(?:\\(?:u[0-9A-Fa-f]{4}|x[0-9A-Fa-f]{2}))+")
#: Bytes of the windows in which compressed bodies are scanned, and how much of one the next repeats.
WINDOW, OVERLAP = 4 << 20, 256 << 10


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """Spans of the three base kinds, per kind leftmost and non-overlapping; matches that are too short are dropped."""
    out: list[tuple[int, int, str]] = []
    low = text.lower()
    if any(x in low for x in ("passw", "secret", "token", "api")):
        out += [(*m.span(), "assign") for m in ASSIGN.finditer(text) if len(m[1]) >= 6]
    if "AKIA" in text:
        out += [(*m.span(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(*m.span(), "hex") for m in HEX.finditer(text)]
    return out


def _more_spans(text: str) -> list[tuple[int, int, str]]:
    out = [(*m.span(), "private_key") for m in _KEY.finditer(text)] if "PRIVATE KEY" in text else []
    return out + ([(*m.span(), "bearer") for m in _BEARER.finditer(text)] if "earer " in text else [])


def _compressed(data: bytes) -> bool:
    return data[:2] == b"\x1f\x8b" or data[:1] == b"\x78" and len(data) > 2 and (data[0] * 256 + data[1]) % 31 == 0


def _plain(data: bytes) -> list[str]:
    """The text of a body that is not compressed, if nearly all of it can be read; bytes that are not UTF-8 count against it."""
    try:
        text, wrong = data.decode("utf-8"), 0
    except UnicodeDecodeError:
        text = data.decode("utf-8", "replace")
        wrong = text.count("\ufffd")
    plain = sum(c.isprintable() or c in "\r\n\t" for c in text) - wrong
    return [text] if text and plain >= 0.95 * len(text) else []


def _windows(data: bytes) -> Iterator[str]:
    """What a compressed body's members hold, in overlapping windows as they unfold, then what follows them."""
    tail, left = b"", data
    while _compressed(left):
        stream = zlib.decompressobj(47)
        try:
            while not stream.eof:
                got = stream.decompress(left, WINDOW)
                left = stream.unconsumed_tail
                if got:
                    yield (tail + got).decode("utf-8", "replace")
                    tail = (tail + got)[-OVERLAP:]
                elif not stream.eof:
                    return
        except zlib.error:
            return
        left = stream.unused_data.lstrip(b"\0")  # members may be padded
    yield from _plain(left)


@dataclass
class Layer:
    """A text; for each character, where in the first text the characters begin and end that it came from, and whether it was decoded."""

    text: str
    starts: np.ndarray
    ends: np.ndarray
    decoded: np.ndarray

    @classmethod
    def alone(cls, text: str, start: int, end: int) -> Layer:
        full = lambda value: np.broadcast_to(np.array(value), len(text))
        return cls(text, full(start), full(end), full(True))

    def place(self, start: int, end: int) -> tuple[int, int]:
        return int(self.starts[start:end].min()), int(self.ends[start:end].max())

    def replaced(self, parts: list[tuple[int, int, list[tuple[int, int, str]]]]) -> Layer:
        """The layer with each (start, end) of parts replaced by strings, each with the range of characters that it came from."""
        texts, starts, ends, decoded, at = [], [], [], [], 0
        for start, end, pieces in parts:
            texts.append(self.text[at:start])
            starts.append(self.starts[at:start]), ends.append(self.ends[at:start]), decoded.append(self.decoded[at:start])
            for a, b, piece in pieces:
                low, high = self.place(a, b)
                texts.append(piece)
                starts.append(np.full(len(piece), low)), ends.append(np.full(len(piece), high)), decoded.append(np.ones(len(piece), bool))
            at = end
        texts.append(self.text[at:])
        return Layer("".join(texts), np.concatenate([*starts, self.starts[at:]]), np.concatenate([*ends, self.ends[at:]]), np.concatenate([*decoded, self.decoded[at:]]))


def _clean(text: str) -> str:
    """Surrogate pairs joined, lone ones replaced."""
    return text.encode("utf-16-le", "surrogatepass").decode("utf-16-le", "replace")


def _percent_parts(text: str) -> list[tuple[int, int, list[tuple[int, int, str]]]]:
    out = []
    for m in _PERCENT.finditer(text):
        got = unquote_to_bytes(m[0]).decode("utf-8", "replace")
        one = len(got) == len(m[0]) // 3
        out.append((*m.span(), [(m.start() + 3 * k, m.start() + 3 * k + 3, c) for k, c in enumerate(got)] if one else [(*m.span(), got)]))
    return out


def _escape_parts(text: str) -> list[tuple[int, int, list[tuple[int, int, str]]]]:
    out = []
    for m in _ESCAPES.finditer(text):
        pieces = [(*e.span(), chr(int(e[1] or e[2], 16))) for e in _ESCAPE.finditer(text, m.start(), m.end())]
        got = "".join(p for _, _, p in pieces)
        out.append((*m.span(), pieces if (clean := _clean(got)) == got else [(*m.span(), clean)]))
    return out


def _joined(text: str) -> list[tuple[int, int, str]]:
    """Base64 bodies that are wrapped over lines: all runs of a match, and each stretch of lines of one width.

    What is before the first whole line and after the last one may belong to a body or not, so both are tried.
    """
    out: dict[tuple[int, int], str] = {}
    for m in _WRAPPED.finditer(text):
        runs = [x.span() for x in _LINE_RUN.finditer(text, m.start(), m.end())]
        widths = [e - s for s, e in runs]
        tries, first = {(0, len(runs))}, 0
        while first < len(runs):
            last = first + 1
            while last < len(runs) and widths[last] == widths[first]:
                last += 1
            end = last + (last < len(runs) and widths[last] < widths[first])
            tries |= {(a, b) for a in (max(0, first - 1), first) for b in (last, end) if b - a > 1}
            first = last
        for a, b in tries:
            body = "".join(text[s:e] for s, e in runs[a:b])
            if len(body) >= 16:
                out[runs[a][0], m.end() if b == len(runs) else runs[b - 1][1]] = body
    return [(*span, body) for span, body in out.items()]


def _body(run: str) -> bytes | None:
    run = run.rstrip("=").replace("-", "+").replace("_", "/")
    if len(run) % 4 == 1:
        return None
    try:
        return base64.b64decode(run + "=" * (-len(run) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def _hidden(layer: Layer) -> Iterator[Layer]:
    """The layers that one layer hides."""
    text = layer.text
    if "%" in text and (parts := _percent_parts(text)):
        yield layer.replaced(parts)
        for m in _RUN.finditer(text):  # escapes may spell a compressed body
            if _PERCENT.search(m[0]) and _compressed(data := unquote_to_bytes(m[0].encode("utf-8", "surrogatepass"))):
                yield from (Layer.alone(w, *layer.place(*m.span())) for w in _windows(data))
    if "\\" in text and (parts := _escape_parts(text)):
        yield layer.replaced(parts)
    parts = []
    for m in _BASE64.finditer(text):
        if data := _body(m[0]):
            if _compressed(data):
                some = False
                for w in _windows(data):
                    some = True
                    yield Layer.alone(w, *layer.place(*m.span()))
                if some:
                    continue
            parts += [(*m.span(), [(*m.span(), plain)]) for plain in _plain(data)]
    if parts:
        yield layer.replaced(parts)
    for start, end, run in _joined(text) if "\n" in text else []:
        if data := _body(run):
            for plain in _windows(data) if _compressed(data) else _plain(data):
                yield Layer.alone(plain, *layer.place(start, end))


def scan(text: str | None) -> tuple:
    text = text or ""
    base = base_spans(text)
    spans = set(base) | set(_more_spans(text))
    places = np.arange(len(text))
    work = [_hidden(Layer(text, places, places + 1, np.zeros(len(text), bool)))]
    digest = lambda layer: hashlib.blake2b(f"{layer.place(0, len(layer.text))}{layer.text}".encode("utf-8", "replace"), digest_size=16).digest()
    seen: set[bytes] = set()
    found = 0
    while work:
        layer = next(work[-1], None)
        if layer is None:
            work.pop()
        elif layer.text and (key := digest(layer)) not in seen:  # a layer seen at this place ends a cycle
            seen.add(key)
            found += 1
            for start, end, kind in base_spans(layer.text) + _more_spans(layer.text):
                if layer.decoded[start:end].any():
                    spans.add((*layer.place(start, end), f"hidden_{kind}"))
            work.append(_hidden(layer))
    counts = [sum(k == kind for _, _, k in base) for kind in BASE]
    return (*counts, hashlib.sha256(render_spans(base, ORDER).encode()).hexdigest(), render_spans(list(spans), ORDER), found)


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: counts and digest of the base kinds, and all spans (code points, end exclusive)."""
    names = ("n_assign", "n_access", "n_hex")
    fields = [(id_col, pa.int64()), *((n, pa.int64()) for n in names), ("base_sha256", pa.string()), ("spans", pa.string()), ("n_layers", pa.int64())]
    schema = f"`{id_col}` long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_layers long"

    def kernel(ids: list, texts: list) -> list:
        return [ids, *zip(*map(scan, texts))] if ids else [[] for _ in fields]

    return map_columns(docs, kernel, schema, pa.schema(fields), id_col, text_col)
