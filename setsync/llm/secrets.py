"""Secrets in whole texts, found through nested encodings.

A worklist starts with the text; every layer is scanned, then its URL escapes, Unicode escapes,
base64 runs (also those wrapped over lines, at all four alignments) and compressed payloads (all their
members, wherever they begin) are unwrapped into new layers until none is new (a text that was seen at
the same place is not taken again, so cycles end; each further copy is reported where it stands). Bytes that are no UTF-8 give way to marks. Each layer keeps,
for every character, the span of the original text it came from; findings are reported there.

Defined cases: null is the empty text, which has no findings; repeated rows are scanned alike; what
inflates beyond ``INFLATE`` bytes is scanned in chunks of that size, each with the last ``OVERLAP`` bytes
of the one before; ``n_unopened`` counts payloads whose decoder would need more than ``DECODER`` bytes.
"""

from __future__ import annotations

import base64
import bz2
import hashlib
import html
import lzma
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from setsync.llm.shared import bounded_batches, table

KINDS = ("assign", "access", "hex")
#: The patterns of the base findings and their least lengths.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
ASSIGN_LENGTH, ACCESS_LENGTH, HEX_LENGTH = 6, 20, 24
ASSIGN_HINTS = ("password", "passwd", "secret", "token", "apikey", "api_key")

BASE64_LENGTH = 16
INFLATE, OVERLAP, DECODER = 32 << 20, 1 << 20, 96 << 20
MASK = "[SECRET]"

URL_ESCAPE = re.compile(r"%[0-9A-Fa-f]{2}")
UNICODE_ESCAPE = re.compile(r"\\u[0-9A-Fa-f]{4}|\\U[0-9A-Fa-f]{8}|\\u\{[0-9A-Fa-f]{1,6}\}|\\x[0-9A-Fa-f]{2}|&#[0-9]{1,7};|&#[xX][0-9A-Fa-f]{1,6};")
URL_RUN = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
WRAPPED_RUN = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]++(?:[ \t]*+\r?\n[ \t]*+[A-Za-z0-9+/_-]++)+")
PACKED = re.compile(rb"\x1f\x8b\x08|\x78[\x01\x5e\x9c\xda]|BZh[1-9]|\xfd7zXZ\x00")
#: Every layer that holds a finding or a further layer has one of these.
TELLING = re.compile(rb"(?i:passw|secret|token|api_?key)|AKIA|[0-9a-f]{24}|%[0-9A-Fa-f]{2}|\\[uUx]|&#|[A-Za-z0-9+/_-]{16}|[A-Za-z0-9+/_-][ \t]*\r?\n[ \t]*[A-Za-z0-9+/_-]")


def byte_set(letters: str) -> np.ndarray:
    known = np.zeros(256, bool)
    known[list(letters.encode())] = True
    return known


LOWER, UPPER, DIGIT = (bytes(range(a, b)).decode() for a, b in ((97, 123), (65, 91), (48, 58)))
HEX_BYTES = byte_set(DIGIT + "abcdef")
BASE64_BYTES = byte_set(LOWER + UPPER + DIGIT + "+/-_")


def runs(text: str, known: tuple[tuple[np.ndarray, int], ...]) -> list[list[tuple[int, int]]]:
    """For each (byte set, least length): spans in code points of the text's longest runs of that set."""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    points = None
    out = []
    for members, least in known:
        gaps = np.flatnonzero(~members[raw])
        edges = np.concatenate([[-1], gaps, [len(raw)]])
        at = np.flatnonzero(np.diff(edges) > least)
        starts, ends = edges[at] + 1, edges[at + 1]
        if len(at) and len(raw) != len(text):
            if points is None:
                points = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
            starts, ends = points[starts], points[ends]
        out.append(list(zip(starts.tolist(), ends.tolist())))
    return out


def scan(text: str, hex_runs: list[tuple[int, int]]) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the base findings of one layer."""
    found = [(s, 2, e) for s, e in hex_runs]
    lowered = text.lower()
    if any(hint in lowered for hint in ASSIGN_HINTS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= ASSIGN_LENGTH]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LENGTH]
    return sorted(found)


class Layer:
    """A decoded text; ``starts``/``ends`` give each character's span in the original (None: itself), ``whole`` one span for all."""

    def __init__(self, text: str, starts=None, ends=None, whole: tuple[int, int] | None = None):
        self.text, self.starts, self.ends, self.whole = text, starts, ends, whole

    def origin(self, s: int, e: int) -> tuple[int, int]:
        if self.whole:
            return self.whole
        if self.starts is None:
            return s, e
        return int(self.starts[s]), int(self.ends[e - 1])

    def key(self) -> tuple[bytes, int, int]:
        """Its text and place: what tells a layer that was read already from another copy of it."""
        return digest(self.text.encode("utf-8", "surrogatepass")), *self.origin(0, len(self.text))

    def inner(self, text: str, starts: np.ndarray, ends: np.ndarray) -> "Layer":
        """A layer over this one; the spans given, which rise, are in this layer's characters."""
        if self.whole:
            return Layer(text, whole=self.whole)
        if self.starts is None:
            return Layer(text, starts, ends)
        return Layer(text, self.starts[starts], self.ends[ends - 1])


def digest(raw: bytes) -> bytes:
    return hashlib.blake2b(raw, digest_size=16).digest()


def unescaped(m: re.Match) -> str | None:
    x = m[0]
    try:
        return html.unescape(x) if x[0] == "&" else chr(int(x[2:].strip("{}"), 16))
    except (ValueError, OverflowError):
        return None


def by_escapes(layer: Layer, pattern: re.Pattern, decode) -> Layer | None:
    """The whole layer with its escapes replaced, each by the characters ``decode`` gives."""
    out, segments, at = [], [], 0  # segments: first and end character here, characters made, whether copied
    for m in pattern.finditer(layer.text):
        got = decode(m)
        if got is None:
            continue
        out += [layer.text[at : m.start()], got]
        segments += [(at, m.start(), m.start() - at, True), (m.start(), m.end(), len(got), False)]
        at = m.end()
    if not segments:
        return None
    out.append(layer.text[at:])
    segments.append((at, len(layer.text), len(layer.text) - at, True))
    first, end, made, copied = (np.array(x) for x in zip(*segments))
    own = np.repeat(np.arange(len(made)), made)
    turn = np.arange(len(own)) - np.repeat(np.cumsum(made) - made, made)
    starts = first[own] + turn * copied[own]
    return layer.inner("".join(out), starts, np.where(copied[own], starts + 1, end[own]))


def url_decoded(m: re.Match) -> str:
    return bytes.fromhex(m[0].replace("%", "")).decode(errors="replace")


def members(raw: bytes, at: int) -> Iterator[bytes]:
    """Pieces of what the members that begin at ``at`` hold, up to damage; at the end the place behind them is returned."""
    magic = PACKED.match(raw, at)[0][:3]
    while raw[at : at + 3] == magic if magic[:1] != b"\x78" else raw[at : at + 1] == b"\x78":
        opener = bz2.BZ2Decompressor() if magic == b"BZh" else lzma.LZMADecompressor(memlimit=DECODER) if magic == b"\xfd7z" else zlib.decompressobj(47)
        given = at
        try:
            while not opener.eof and given < len(raw):
                piece, given = raw[given : given + 1024], given + 1024
                while True:
                    out = opener.decompress(piece, 1 << 20)
                    if out:
                        yield out
                    piece = opener.unconsumed_tail if hasattr(opener, "unconsumed_tail") else b""
                    if opener.eof or not (piece or len(out) == 1 << 20 or not getattr(opener, "needs_input", True)):
                        break
        except (zlib.error, OSError, EOFError, ValueError):
            break
        except lzma.LZMAError as e:
            if "emory" in str(e):
                raise OverflowError from e
            break
        if not opener.eof:
            break
        at = min(given, len(raw)) - len(opener.unused_data)
    return at


def inflated(raw: bytes) -> Iterator[bytes | None]:
    """What each compressed payload in ``raw`` holds, in overlapping chunks; None for one too large for its decoder."""
    at = 0
    while m := PACKED.search(raw, at):
        at, parts, size = m.end(), [], 0
        pieces = members(raw, m.start())
        while True:
            try:
                piece = next(pieces)
            except StopIteration as done:
                at = max(at, done.value)
                break
            except OverflowError:
                yield None
                break
            parts.append(piece)
            size += len(piece)
            if size >= INFLATE:
                yield (chunk := b"".join(parts))
                parts, size = [chunk[-OVERLAP:]], OVERLAP
        if parts:
            yield b"".join(parts)


def readable(text: str) -> bool:
    return len(text) >= ASSIGN_LENGTH and all(c.isprintable() or c in "\t\n\r" for c in text)


def decoded(raw: bytes) -> tuple[str, np.ndarray] | None:
    """Text of the bytes (a mark for each that is no UTF-8) and where its characters end; None if nothing can be found in it."""
    text = raw.decode(errors="surrogateescape")
    if not TELLING.search(raw) and not readable(text):
        return None
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    bad = (codes >= 0xDC80) & (codes <= 0xDCFF)
    sizes = np.where(bad, 1, 1 + (codes >= 0x80) + (codes >= 0x800) + (codes >= 0x10000).astype(np.int64))
    if bad.any():
        text = np.where(bad, 0xFFFD, codes).astype("<u4").tobytes().decode("utf-32-le")
    return text, np.cumsum(sizes)


def opened(layer: Layer, s: int, e: int, seen: set[tuple[bytes, int, int]]) -> Iterator[Layer | None]:
    """Layers inside the base64 run [s, e), which may hold line breaks: its text at each alignment, and what
    compressed payloads in it hold; None for one that cannot be opened."""
    body = layer.text[s:e]
    spots = np.arange(s, e)
    if not body.isascii() or "\n" in body:
        letters = np.array([not c.isspace() for c in body])
        body, spots = "".join(body.split()), spots[letters]
    body = body.replace("-", "+").replace("_", "/")
    for shift in range(4):
        n = len(body) - shift
        n -= n % 4 == 1
        if n < ASSIGN_LENGTH:
            continue
        raw = base64.b64decode(body[shift : shift + n] + "=" * (-n % 4))
        if got := decoded(raw):
            text, upto = got
            at = np.concatenate([[0], upto[:-1]])
            yield layer.inner(text, spots[shift + at * 4 // 3], spots[np.minimum(shift - (-upto * 4 // 3), len(body)) - 1] + 1)
        place = layer.origin(s, e)
        work = [inflated(raw)]  # depth first, so of each level one chunk is held
        while work:
            content = next(work[-1], b"")
            if content is None:
                yield None
            elif not content:
                work.pop()
            elif (mark := (digest(content), *place)) not in seen:
                seen.add(mark)
                work.append(inflated(content))
                if got := decoded(content):
                    yield Layer(got[0], whole=place)


def base64_spans(text: str, lone: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Runs wrapped over lines as one, and the ``lone`` ones outside them."""
    if "\n" not in text:
        return lone
    joined = [m.span() for m in WRAPPED_RUN.finditer(text) if m.end() - m.start() > BASE64_LENGTH]
    edges = np.array([x for span in joined for x in span])
    return joined + [r for r in lone if not np.searchsorted(edges, r[0], "right") % 2]


def inside(layer: Layer, base64_runs: list[tuple[int, int]], seen: set[tuple[bytes, int, int]]) -> Iterator[Layer | None]:
    """The layers that a layer holds, each made when it is asked for; None for what cannot be opened."""
    if "%" in layer.text and URL_ESCAPE.search(layer.text) and (new := by_escapes(layer, URL_RUN, url_decoded)):
        yield new
    if ("\\" in layer.text or "&#" in layer.text) and (new := by_escapes(layer, UNICODE_ESCAPE, unescaped)):
        yield new
    for s, e in base64_spans(layer.text, base64_runs):
        yield from opened(layer, s, e, seen)


def find_secrets(text: str | None) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]], int, int]:
    """Base findings, all findings (start, kind, end) in the original, layers read, payloads left unopened."""
    base: list[tuple[int, int, int]] = []
    every: set[tuple[int, int, int]] = set()
    work, seen, contents, layers, unopened = [iter([Layer(text or "")])], set(), set(), 0, 0
    while work:
        try:
            layer = next(work[-1])
        except StopIteration:
            work.pop()
            continue
        if layer is None:
            unopened += 1
            continue
        if not layer.text or (mark := layer.key()) in seen:
            continue
        seen.add(mark)
        layers += 1
        hex_runs, base64_runs = runs(layer.text, ((HEX_BYTES, HEX_LENGTH), (BASE64_BYTES, BASE64_LENGTH)))
        found = scan(layer.text, hex_runs)
        if layers == 1:
            base = found
        for s, kind, e in found:
            a, b = layer.origin(s, e)
            every.add((a, kind, b))
        work.append(inside(layer, base64_runs, contents))
    return base, sorted(every), layers, unopened


def spelled(found: list[tuple[int, int, int]]) -> str:
    return ",".join([f"{KINDS[k]}:{s}:{e}" for s, k, e in found])


def masked(text: str | None, found: list[tuple[int, int, int]]) -> str | None:
    """The text with every found span (overlapping ones as one) replaced by ``MASK``."""
    if not found:
        return text
    out, at = [], 0
    for s, _, e in sorted(found):
        if s >= at:
            out += [text[at:s], MASK]
        at = max(at, e)
    return "".join([*out, text[at:]])


RESULT = T.StructType(
    [T.StructField(f"n_{k}", T.LongType()) for k in KINDS]
    + [T.StructField(n, T.StringType()) for n in ("base_sha256", "spans")]
    + [T.StructField(n, T.LongType()) for n in ("n_layers", "n_unopened")]
)


@F.pandas_udf(RESULT)
def secrets_column(text: pd.Series) -> pd.DataFrame:
    rows = []
    for t in text:
        base, every, layers, unopened = find_secrets(t)
        kinds = [k for _, k, _ in base]
        rows.append((*[kinds.count(k) for k in range(3)], hashlib.sha256(spelled(base).encode()).hexdigest(), spelled(every), layers, unopened))
    return pd.DataFrame(rows, columns=RESULT.names)


@F.pandas_udf(T.StringType())
def masked_column(text: pd.Series) -> pd.Series:
    return pd.Series([masked(t, find_secrets(t)[1]) for t in text], dtype=object)


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id``, counts of base findings, their digest, all spans, layers read."""
    bounded_batches(docs.sparkSession)
    found: Column = secrets_column(F.col(text_col))
    return docs.select(F.col(id_col).alias("doc_id"), found.alias("found")).select("doc_id", "found.*")


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(table(spark, sf_dir, "documents"))
