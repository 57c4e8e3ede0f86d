"""Secret scans over texts and everything that is encoded inside them.

Each text is a worklist of layers. A layer is scanned, its encoded parts (URL
escapes, Unicode escapes, base64, UTF-16, compressed data) are decoded into new
layers, and so on until no new layer appears; a layer that has the content and the
span of one seen before isn't opened again, an equal one from another place of the
text is. Every character of a layer knows the span of the text it came from, so
secrets found deep inside are reported as spans of the text. What a layer knows is
runs of positions, so it takes little more memory than its characters.
"""

from __future__ import annotations

import base64
import bz2
import hashlib
import lzma
import re
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_pass

#: The kinds of secrets, in their order.
KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
#: Least length of an assigned value.
VALUE = 12

#: A word that one of these lower-case parts is in may open an assignment.
_HINTS = ("password", "passwd", "secret", "token", "apikey", "api_key")

PERCENT = re.compile(r"[^\s%]*(?:%[0-9A-Fa-f]{2}[^\s%]*)+")
ESCAPES = re.compile(r"(?:\\u\{[0-9A-Fa-f]{1,6}\}|\\u[0-9A-Fa-f]{4}|\\U[0-9A-Fa-f]{8}|\\x[0-9A-Fa-f]{2}|&#x[0-9A-Fa-f]{1,6};|&#[0-9]{1,7};)")
#: A run of base64 characters, with the lines that it is wrapped onto.
BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}(?:[\x20\t]*\r?\n[\x20\t]*[A-Za-z0-9+/_-]+)*={0,2}")
_LINE = re.compile(r"[A-Za-z0-9+/_-]+")
#: No secret, and nothing that encodes one, is shorter than these ASCII characters in a row.
_LEGIBLE = re.compile(rb"[\t\n\r\x20-\x7e]{16}")
_MAGIC = re.compile(rb"\x1f\x8b\x08|BZh[1-9](?:1AY&SY|\x17rE8P\x90)|\xfd7zXZ\x00")

#: The same as 16-bit units, low or high byte first.
_WIDE = (re.compile(rb"(?:[\t\n\r\x20-\x7e]\x00){16,}"), re.compile(rb"(?:\x00[\t\n\r\x20-\x7e]){16,}"))

#: Bytes of decompressed data that are scanned at once, and how many of them the next window has again.
WINDOW, AGAIN = 1 << 24, 1 << 20


def scan(text: str) -> list[tuple[str, int, int]]:
    """Secrets of one layer, per kind leftmost and non-overlapping."""
    out = []
    low = text.lower()
    if any(h in low for h in _HINTS):
        out += [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if len(m.group(2)) >= VALUE]
    if "AKIA" in text:
        out += [("access", m.start(), m.end()) for m in ACCESS.finditer(text)]
    out += [("hex", m.start(), m.end()) for m in HEX.finditer(text)]
    return out


class Runs:
    """Where units came from: pieces that start at `out` units and `src` positions, each a stretch of single positions or one unit of `width` positions."""

    def __init__(self, out, src, width) -> None:
        self.out, self.src, self.width = (np.asarray(v, np.int64) for v in (out, src, width))

    def span(self, i: int) -> tuple[int, int]:
        k = int(np.searchsorted(self.out, i, "right")) - 1
        at, width = int(self.src[k]), int(self.width[k])
        return (at, at + width) if width else (at + i - int(self.out[k]), at + i - int(self.out[k]) + 1)


@dataclass
class Layer:
    """Decoded text; `span` gives the span in the parent that the character at an index came from."""

    text: str
    span: Callable[[int], tuple[int, int]] | None = None
    parent: Layer | None = None

    def to_text(self, start: int, end: int) -> tuple[int, int]:
        """Span of the original text that a span of this layer came from."""
        layer: Layer | None = self
        while layer is not None and layer.parent is not None:
            start, end = layer.span(start)[0], layer.span(max(start, end - 1))[1]
            layer = layer.parent
        return start, end


def _utf8_layer(data: bytes, byte_span: Callable[[int], tuple[int, int]], parent: Layer) -> Layer:
    """A layer from bytes that each came from a span of the parent; bytes that aren't UTF-8 become U+FFFD."""
    if data.isascii():
        return Layer(data.decode("ascii"), byte_span, parent)
    text = data.decode("utf-8", "surrogateescape")
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    size = (1 + (points >= 0x80) + (points >= 0x800) + (points >= 0x10000)).astype(np.int8)
    size[(points >= 0xDC80) & (points <= 0xDCFF)] = 1
    first = np.concatenate([[0], np.cumsum(size, dtype=np.int32)]).astype(np.int32)
    span = lambda i: (byte_span(int(first[i]))[0], byte_span(int(first[i + 1]) - 1)[1])
    return Layer(_BAD.sub("\ufffd", text), span, parent)


_BAD = re.compile("[\udc80-\udcff]")
_HEX = np.full(256, 255, np.uint8)
for _c in b"0123456789abcdefABCDEF":
    _HEX[_c] = int(chr(_c), 16)


def _percent(layer: Layer) -> Iterator[Layer]:
    if "%" not in layer.text:
        return
    for m in PERCENT.finditer(layer.text):
        part = m.group()
        raw = np.frombuffer(part.encode("utf-8", "surrogatepass"), np.uint8)
        value = _HEX[raw]
        at = np.flatnonzero((raw[:-2] == 0x25) & (value[1:-1] < 16) & (value[2:] < 16))
        out = raw.copy()
        out[at] = value[at + 1] * 16 + value[at + 2]
        keep = np.ones(len(raw), bool)
        keep[at + 1] = keep[at + 2] = False
        # pieces alternate: an escape of three characters, then what stands up to the next
        unit = at - 2 * np.arange(len(at))
        char = np.arange(len(raw) + 1, dtype=np.int64) if part.isascii() else np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
        starts = np.concatenate([[0], np.stack([unit, unit + 1], 1).ravel()])
        sources = np.concatenate([[0], np.stack([at, at + 3], 1).ravel()])
        widths = np.concatenate([[0], np.tile([3, 0], len(at))])
        runs, ascii_, base = Runs(starts, sources, widths), part.isascii(), m.start()

        def byte_span(i: int, runs=runs, char=char, ascii_=ascii_, base=base) -> tuple[int, int]:
            a, z = runs.span(i)
            # a byte inside a character stands for all of it
            return (base + a, base + z) if ascii_ else (base + int(char[a + 1]) - 1, base + int(char[z]))

        yield _utf8_layer(out[keep].tobytes(), byte_span, layer)


def _escaped(layer: Layer) -> Iterator[Layer]:
    """Words with Unicode escapes: each escape becomes its character."""
    if "\\" not in layer.text and "&#" not in layer.text:
        return
    hits = list(ESCAPES.finditer(layer.text))
    k = 0
    while k < len(hits):
        # a run of escapes and what stands between them without a blank
        j = k
        while j + 1 < len(hits) and not re.search(r"\s", layer.text[hits[j].end() : hits[j + 1].start()]):
            j += 1
        start, end = hits[k].start(), hits[j].end()
        while start and not layer.text[start - 1].isspace():
            start -= 1
        while end < len(layer.text) and not layer.text[end].isspace():
            end += 1
        chars, out, src, width = [], [], [], []
        n, i = 0, start

        def plain(a: int, z: int) -> None:
            nonlocal n
            if z > a:
                chars.append(layer.text[a:z])
                out.append(n), src.append(a), width.append(0)
                n += z - a

        m = k
        while m <= j:
            h = hits[m]
            plain(i, h.start())
            number, last = _number(h), h
            # two halves of a surrogate pair make one character
            if 0xD800 <= number < 0xDC00 and m < j and hits[m + 1].start() == h.end() and 0xDC00 <= _number(hits[m + 1]) < 0xE000:
                last = hits[m + 1]
                number = 0x10000 + ((number - 0xD800) << 10) + _number(last) - 0xDC00
                m += 1
            if number < 0x110000:
                chars.append("\ufffd" if 0xD800 <= number < 0xE000 else chr(number))
                out.append(n), src.append(h.start()), width.append(last.end() - h.start())
                n += 1
            i = last.end()
            m += 1
        plain(i, end)
        yield Layer("".join(chars), Runs(out, src, width).span, layer)
        k = j + 1


def _number(m: re.Match) -> int:
    """The code point that an escape names."""
    decimal = m.group()[:2] == "&#" and m.group()[2] != "x"
    return int(m.group().strip("\\uUx{}&#;"), 10 if decimal else 16)


def _unpacker(head: bytes):
    """A new decompressor for data that begins like this; None if it isn't compressed."""
    if head[:2] == b"\x1f\x8b":
        return zlib.decompressobj(31)
    if head[:3] == b"BZh":
        return bz2.BZ2Decompressor()
    if head[:6] == b"\xfd7zXZ\x00":
        return lzma.LZMADecompressor()
    if len(head) > 2 and head[0] == 0x78 and (head[0] * 256 + head[1]) % 31 == 0:
        return zlib.decompressobj()
    return None


def _unpacked(parts: Iterator[bytes]) -> Iterator[bytes]:
    """What compressed data holds, all its members, in pieces of bounded size; broken data gives what comes before the break."""
    z, rest = None, b""
    try:
        for part in parts:
            rest += part
            while rest:
                if z is None:
                    # members may be filled up with zeros; a head needs its first bytes
                    rest = rest.lstrip(b"\0")
                    if len(rest) < 8 and (more := next(parts, None)) is not None:
                        rest += more
                        continue
                    if not rest or (z := _unpacker(rest)) is None:
                        break
                out = z.decompress(rest, AGAIN)
                rest = getattr(z, "unconsumed_tail", b"")
                if out:
                    yield out
                # bz2 and lzma keep their input; zlib may hold output back when its input is used up
                while not z.eof and not rest and (len(out) == AGAIN or not getattr(z, "needs_input", True)):
                    out = z.decompress(b"", AGAIN)
                    if out:
                        yield out
                if z.eof:
                    rest, z = z.unused_data, None
            if z is None and rest:
                return
    except (zlib.error, OSError, EOFError, ValueError, lzma.LZMAError):
        return


def _pieces(data) -> Iterator[bytes]:
    view = memoryview(data)
    for i in range(0, len(view), AGAIN):
        yield bytes(view[i : i + AGAIN])


def _contents(data) -> Iterator[tuple[bytes, bool]]:
    """Compressed data, and what is compressed in it, unpacked; in windows that overlap, each with whether another follows."""
    parts, seen = _pieces(data), set()
    held = next(parts, b"")
    depth = 0
    while _unpacker(held) is not None:
        inner = _unpacked(chain([held], parts))
        first = bytearray()
        for piece in inner:
            first += piece
            if len(first) >= WINDOW:
                break
        if not first:
            if not depth:
                return
            break
        # data that unpacks to itself ends here
        digest = hashlib.blake2b(first, digest_size=16).digest()
        if digest in seen:
            return
        seen.add(digest)
        held, parts, depth = bytes(first), inner, depth + 1
    if not depth:
        return
    window = bytearray(held)
    for piece in parts:
        if len(window) >= WINDOW:
            yield bytes(window), True
            del window[:-AGAIN]
        window += piece
    yield bytes(window), False


def _wide(data: bytes) -> Iterator[tuple[int, bytes]]:
    """Legible stretches of 16-bit units: where their ASCII bytes begin, and these (every other byte)."""
    if b"\x00" in data:
        for high, pattern in enumerate(_WIDE):
            for m in pattern.finditer(data):
                yield m.start() + high, m.group()[high::2]


def _base64(layer: Layer, cuts: list[int]) -> Iterator[Layer]:
    """Base64 may begin at any character of a run: the four alignments decode every beginning."""
    for m in BASE64.finditer(layer.text):
        lines = [x.span() for x in _LINE.finditer(layer.text, m.start(), m.end())]
        yield from _decoded(layer, lines, cuts)
        if len(lines) > 1:
            for line in lines:
                if line[1] - line[0] >= 16:
                    yield from _decoded(layer, [line], cuts)


def _decoded(layer: Layer, lines: list[tuple[int, int]], cuts: list[int]) -> Iterator[Layer]:
    plain = "".join(layer.text[a:z] for a, z in lines).translate(_URL_SAFE)
    size = np.concatenate([[0], np.cumsum([z - a for a, z in lines])])
    places = Runs(size[:-1], [a for a, _ in lines], np.zeros(len(lines)))
    end = lines[-1][1]
    symbols = np.frombuffer(plain.encode("ascii"), np.uint8)
    starts = np.unique(np.concatenate([size[:-1], np.flatnonzero((symbols == 0x2B) | (symbols == 0x2F)) + 1]))
    for skip in range(4):
        n = len(plain) - skip
        n -= n % 4 == 1
        data = base64.b64decode(plain[skip : skip + n] + "=" * (-n % 4))
        view = np.frombuffer(data, np.uint8)
        own = (starts[(starts >= skip) & (starts % 4 == skip)] - skip) // 4 * 3
        own = own[own < len(view)]
        heads = sorted({m.start() for m in _MAGIC.finditer(data)} | set(own[view[own] == 0x78].tolist()))
        packed = False
        for at in heads:
            whole = (places.span(skip + at // 3 * 4)[0], end)
            for content, more in _contents(memoryview(data)[at:]):
                packed = packed or not at
                cuts[0] += more
                if _LEGIBLE.search(content):
                    yield Layer(content.decode("utf-8", "replace"), lambda i, w=whole: w, layer)
                for _, letters in _wide(content):
                    yield Layer(letters.decode("ascii"), lambda i, w=whole: w, layer)

        # three bytes from four characters: each byte from the characters that hold its bits
        def byte_span(i: int, skip: int = skip, n: int = n) -> tuple[int, int]:
            last = min(n, -(-(i + 1) * 4 // 3)) - 1
            return places.span(skip + i * 4 // 3)[0], places.span(skip + last)[1]

        for at, letters in _wide(data):
            yield Layer(letters.decode("ascii"), lambda i, f=byte_span, at=at: f(at + 2 * i), layer)
        # data without a legible stretch holds no secret and nothing that encodes one
        if not packed and _LEGIBLE.search(data):
            yield _utf8_layer(data, byte_span, layer)


_URL_SAFE = str.maketrans("-_", "+/")


def scan_deep(text: str) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]], int, int]:
    """Secrets of the text itself, those of its layers as spans of the text, the number of layers opened and of window ends inside decompressed data."""
    base = scan(text)
    known = {text: base}
    seen: set[tuple[str, int, int]] = {(text, 0, len(text))}
    work = [Layer(text)]
    found: set[tuple[str, int, int]] = set()
    layers, cuts = 0, [0]
    while work:
        layer = work.pop()
        for new in chain(_percent(layer), _escaped(layer), _base64(layer, cuts)):
            if not new.text or (key := (new.text, *new.to_text(0, len(new.text)))) in seen:
                continue
            seen.add(key)
            layers += 1
            if new.text not in known:
                known[new.text] = scan(new.text)
            found |= {(k, *new.to_text(s, e)) for k, s, e in known[new.text]}
            work.append(new)
    return base, sorted(found - set(base)), layers, cuts[0]


def joined(spans: list[tuple[str, int, int]]) -> str:
    order = sorted(spans, key=lambda x: (x[1], KINDS.index(x[0]), x[2]))
    return ",".join(f"{k}:{s}:{e}" for k, s, e in order)


_OUT = pa.schema([("doc_id", pa.int64()), ("n_assign", pa.int64()), ("n_access", pa.int64()), ("n_hex", pa.int64()), ("base_sha256", pa.string()), ("spans", pa.string()), ("n_layers", pa.int64()), ("n_cuts", pa.int64())])


def _scan_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        texts = b.column("text")
        for i, doc_id in enumerate(b.column("doc_id").to_pylist()):
            base, more, layers, cuts = scan_deep(texts[i].as_py() or "")
            count = [sum(k == kind for k, _, _ in base) for kind in KINDS]
            rows.append((doc_id, *count, hashlib.sha256(joined(base).encode()).hexdigest(), joined(base + more), layers, cuts))
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _OUT.types)], schema=_OUT)


def scan_documents(docs: DataFrame) -> DataFrame:
    """Secrets of every document, as spans of code points of its text.

    Null text counts as empty. Spans that only layers show stand beside the base
    spans in `spans`; n_layers counts the layers opened, n_cuts the ends of windows
    inside decompressed data: windows share 1 MiB, so only what is longer than that
    may be cut there. Texts are scanned whole, however long. An empty table gives an
    empty result; repeated rows each get a row; extra columns are ignored.
    """
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return arrow_pass(slim, _scan_batches, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_layers long, n_cuts long")
