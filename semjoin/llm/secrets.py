"""Secret scans through nested encodings: a worklist of decoded layers, each scanned, spans mapped back."""

from __future__ import annotations

import base64
import binascii
import bz2
import hashlib
import itertools
import lzma
import re
import zlib
from bisect import bisect_right
from collections.abc import Iterator

import pandas as pd
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Kinds in their listed order, and their patterns.
KINDS = ("assign", "access", "hex")
_ASSIGN = re.compile(r"((?i:password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.ASCII)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{24,}")
_WORDS = ("passw", "secret", "token", "api")

_PERCENT = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
_ESCAPE = re.compile(r"(?:\\u[0-9A-Fa-f]{4}|\\x[0-9A-Fa-f]{2}|\\U[0-9A-Fa-f]{8}|\\u\{[0-9A-Fa-f]{1,6}\}|&#[0-9]{1,7};|&#[xX][0-9A-Fa-f]{1,6};)+")
_ONE = re.compile(r"\\u\{([0-9A-Fa-f]+)\}|\\[uUx]([0-9A-Fa-f]+)|&#[xX]([0-9A-Fa-f]+);|&#([0-9]+);")
_BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
_WRAPPED = re.compile(r"[A-Za-z0-9+/_-]{16,}+(?:[ \t]*+\r?\n[ \t]*+[A-Za-z0-9+/_-]++)++={0,2}")
_LINE, _BREAK = re.compile(r"[A-Za-z0-9+/_=-]+"), re.compile(r"[ \t\r\n]+")
#: Unpacked layers are scanned in pieces of this many bytes that overlap, so memory stays bounded.
PIECE, OVERLAP = 1 << 23, 1 << 12
#: Streams that may be none are fed by slices of so many bytes.
STEP = 1 << 16


def scan(text: str) -> list[tuple[int, int, int]]:
    """(start, end, kind number) of the base patterns, leftmost and non-overlapping for each kind."""
    out = []
    low = text.lower()
    if any(w in low for w in _WORDS):
        out += [(*m.span(), 0) for m in _ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        out += [(*m.span(), 1) for m in _ACCESS.finditer(text) if len(m[0]) >= 20]
    out += [(*m.span(), 2) for m in _HEX.finditer(text)]
    return sorted(out, key=lambda x: (x[0], x[2]))


class Layer:
    """A text with its way back: segments of the parent's text, copied or decoded, in order."""

    def __init__(self, text: str, parent: Layer | None = None, starts=(), sources=(), how: str = ""):
        self.text, self.parent, self.starts, self.sources = text, parent, starts, sources
        self.name = f"{parent.name}+{how}".lstrip("+") if parent else ""

    def root_span(self, start: int, end: int) -> tuple[int, int] | None:
        """Span in the root text, or None if the span lies in copied text alone, at this layer."""
        if self.parent is None:
            return start, end
        a, b = bisect_right(self.starts, start) - 1, bisect_right(self.starts, max(start, end - 1)) - 1
        if not any(self.sources[k][2] for k in range(a, b + 1)):
            return None
        s, e = self.sources[a], self.sources[b]
        lo = s[0] if s[2] else s[0] + start - self.starts[a]
        hi = e[1] if e[2] else e[0] + end - self.starts[b]
        return self.parent._up(lo, hi)

    def _up(self, start: int, end: int) -> tuple[int, int]:
        if self.parent is None:
            return start, end
        a, b = bisect_right(self.starts, start) - 1, bisect_right(self.starts, max(start, end - 1)) - 1
        s, e = self.sources[a], self.sources[b]
        return self.parent._up(s[0] if s[2] else s[0] + start - self.starts[a], e[1] if e[2] else e[0] + end - self.starts[b])


def _rewritten(layer: Layer, pattern: re.Pattern, decode, how: str) -> Layer | None:
    """The layer with each match of pattern decoded, or None if nothing changed."""
    parts, starts, sources, at, size = [], [], [], 0, 0

    def add(piece: str, a: int, b: int, decoded: bool) -> None:
        nonlocal size
        if piece:
            parts.append(piece)
            starts.append(size)
            sources.append((a, b, decoded))
            size += len(piece)

    for m in pattern.finditer(layer.text):
        new = decode(m[0])
        if new is not None and new != m[0]:
            add(layer.text[at : m.start()], at, m.start(), False)
            add(new, *m.span(), True)
            at = m.end()
    if not at:
        return None
    add(layer.text[at:], at, len(layer.text), False)
    return Layer("".join(parts), layer, starts, sources, how)


def _percent(s: str) -> str:
    return bytes.fromhex(s.replace("%", "")).decode("utf-8", "replace")


def _escape(s: str) -> str | None:
    codes = [int(m[4]) if m[4] else int(m[1] or m[2] or m[3], 16) for m in _ONE.finditer(s)]
    if any(c > 0x10FFFF for c in codes):
        return None
    return "".join(map(chr, codes)).encode("utf-16-le", "surrogatepass").decode("utf-16-le", "replace")


class _Zstd:
    """A frame of zstd, fed in slices so short that what comes out at once stays bounded."""

    SLICE = 256

    def __init__(self):
        self.feed, self.left, self.eof, self.unused_data = zstandard.ZstdDecompressor(max_window_size=1 << 27).decompressobj(), b"", False, b""

    @property
    def needs_input(self) -> bool:
        return not self.left

    def decompress(self, data: bytes, _most: int) -> bytes:
        view, at, out = memoryview(self.left + data if self.left else data), 0, []
        size = 0
        while at < len(view) and size < PIECE and not self.feed.eof:
            got = self.feed.decompress(bytes(view[at : at + self.SLICE]))
            out.append(got)
            size, at = size + len(got), at + self.SLICE
        self.left = bytes(view[at:])
        if self.feed.eof:
            self.eof, self.unused_data, self.left = True, self.feed.unused_data + self.left, b""
        return b"".join(out)


#: Formats: how to start a decompressor.
_FEEDS = {"gzip": lambda: zlib.decompressobj(31), "zlib": zlib.decompressobj, "bz2": bz2.BZ2Decompressor, "xz": lambda: lzma.LZMADecompressor(memlimit=1 << 27), "zstd": _Zstd}
_HEAD = 6


def packing_of(data: bytes) -> str | None:
    """Name of the compression of data, by its first bytes."""
    if data[:2] == b"\x1f\x8b":
        return "gzip"
    if data[:1] == b"\x78" and len(data) > 2 and (data[0] << 8 | data[1]) % 31 == 0:
        return "zlib"
    if data[:3] == b"BZh":
        return "bz2"
    if data[:6] == b"\xfd7zXZ\x00":
        return "xz"
    if data[:4] == b"\x28\xb5\x2f\xfd":
        return "zstd"
    return None


def _gathered(pieces: Iterator[bytes]) -> Iterator[bytes]:
    """The same bytes in pieces of PIECE or more, but for the last one."""
    held, size = [], 0
    for piece in pieces:
        held.append(piece)
        size += len(piece)
        if size >= PIECE:
            yield b"".join(held)
            held, size = [], 0
    if size:
        yield b"".join(held)


class _Unpacked:
    """What compressed pieces of bytes unpack to, over all members in a row, a bounded piece at a time; ends at damage.

    After that, `rest` has the pieces behind the last member."""

    def __init__(self, name: str, source: Iterator[bytes]):
        self.name, self.source, self.rest, self.empty = name, source, iter(()), True

    def __iter__(self) -> Iterator[bytes]:
        feed, data = _FEEDS[self.name](), next(self.source, b"")
        try:
            while True:
                out = feed.decompress(data, PIECE)
                if out:
                    self.empty = False
                    yield out
                if feed.eof:
                    self.empty = False
                    data = feed.unused_data.lstrip(b"\0")
                    while len(data) < _HEAD and (more := next(self.source, b"")):
                        data = (data + more).lstrip(b"\0")
                    if packing_of(data) != self.name:
                        self.rest = itertools.chain([data] if data else [], self.source)
                        return
                    feed = _FEEDS[self.name]()
                    continue
                data = getattr(feed, "unconsumed_tail", b"")
                if not data and (feed.needs_input if hasattr(feed, "needs_input") else len(out) < PIECE):
                    data = next(self.source, b"")
                    if not data:
                        return
        except (OSError, EOFError, ValueError, zlib.error, lzma.LZMAError, zstandard.ZstdError):
            return


#: What UTF-16 looks like where every other byte of the text is zero, by the parity of the zeros.
_WIDE = ("utf-16-be", "utf-16-le")
#: Parts of decoded bytes that read as text: so many printable characters in a row at least.
_READABLE = re.compile(r"[^\x00-\x08\x0b\x0c\x0e-\x1f\x7f-\x9f�]{8,}")
#: First bytes of streams that can begin anywhere in decoded bytes; zlib's two are too common for that.
_MAGIC = re.compile(rb"\x1f\x8b\x08|BZh[1-9]1AY&SY|\xfd7zXZ\x00|\x28\xb5\x2f\xfd")


def _wide(data: bytes) -> str | None:
    """The UTF-16 that data looks like, by its mark or its zero bytes."""
    if data[:2] in (b"\xfe\xff", b"\xff\xfe"):
        return _WIDE[data[:1] == b"\xff"]
    pairs = len(data) // 2
    for parity, name in enumerate(_WIDE):
        if pairs >= 4 and data[parity : 2 * pairs : 2].count(0) >= 0.7 * pairs > 7 * data[1 - parity : 2 * pairs : 2].count(0):
            return name
    return None


def _plain(data: bytes) -> str | None:
    """data as text, if it is text from end to end."""
    try:
        text = data.decode(_wide(data) or "utf-8")
    except UnicodeDecodeError:
        return None
    return text if sum(c.isprintable() or c in "\t\r\n" for c in text) >= 0.95 * len(text) else None


def _texts(data: bytes, how: str) -> Iterator[tuple[str, str]]:
    """Texts in decoded bytes: the bytes as text, or what they unpack to, which may be packed again."""
    if packing_of(data) is not None:
        yield from _unpacked_texts(iter([data]), how)
    elif (text := _plain(data)) is not None:
        yield text, how


def _stray(data: bytes, start: int, how: str) -> Iterator[tuple[str, str]]:
    """Texts of a stream that may begin at start; what is none ends at its first slice."""
    slices = (data[i : i + STEP] for i in range(start, len(data), STEP))
    head = next(slices)
    name = packing_of(head)
    if name is not None:
        yield from _unpacked_texts(iter(_Unpacked(name, itertools.chain([head], slices))), f"{how}+{name}", 1)


def _parts(data: bytes, how: str) -> Iterator[tuple[str, str]]:
    """Texts in bytes that have something else before or after them: readable parts and streams by their first bytes."""
    for m in _MAGIC.finditer(data):
        yield from _stray(data, m.start(), how)
    name = _wide(data[3:-3]) if len(data) > 16 else None
    for start in (0, 1) if name in _WIDE else (0,):
        for m in _READABLE.finditer(data[start:].decode(name or "utf-8", "replace")):
            yield m[0], how


def _unpacked_texts(source: Iterator[bytes], how: str, depth: int = 0) -> Iterator[tuple[str, str]]:
    """Texts in pieces of bytes, each stream unpacked as it comes. What a damaged or cut stream gave counts;
    bytes behind a stream, or that are none after all, are looked at in the same way."""
    pieces = _gathered(source)
    while head := next(pieces, b""):
        name = packing_of(head) if depth < 32 else None
        if name is not None:
            stream = _Unpacked(name, itertools.chain([head], pieces))
            yield from _unpacked_texts(iter(stream), f"{how}+{name}", depth + 1)
            if not stream.empty:
                pieces = _gathered(stream.rest)
                continue
        wide, tail = _wide(head), b""
        for piece in itertools.chain([head], pieces):
            whole = tail + piece
            yield whole.decode(wide or "utf-8", "replace"), how
            # An even overlap, so that characters of two bytes stay whole from piece to piece.
            tail = whole[-OVERLAP - len(whole) % 2 :]
        return


def _from_base64(body: str) -> bytes | None:
    body = body.rstrip("=")
    if len(body) % 4 == 1:
        return None
    try:
        return base64.b64decode(body.replace("-", "+").replace("_", "/") + "=" * (-len(body) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def _wrapped(text: str) -> Iterator[list[tuple[int, int]]]:
    """Base64 over several lines, as lists of the spans that could be one value, the likeliest first.

    Lines of one width belong together, with the line before them, which may be of another width as something can stand
    before the value, and with a shorter line after them. Either of the two may be foreign."""
    for m in _WRAPPED.finditer(text):
        lines = [(m.start() + x.start(), m.start() + x.end()) for x in _LINE.finditer(m[0])]
        size, i = [b - a for a, b in lines], 0
        while i + 1 < len(lines):
            j = i + 1
            while j + 1 < len(lines) and size[j + 1] == size[i + 1]:
                j += 1
            ends = [j + 1, j] if j + 1 < len(lines) and size[j + 1] < size[j] else [j]
            starts = [i] if size[i] == size[i + 1] else [i, i + 1]
            yield [(lines[s][0], lines[e][1]) for s in starts for e in ends if e > s]
            i = j + 1


def _shifted(body: str) -> Iterator[tuple[str, str]]:
    """Texts of base64 that letters of its own alphabet stand before or behind, as in blob/cGFz: all four alignments."""
    body = body.rstrip("=").replace("-", "+").replace("_", "/")
    for start in range(4):
        stop = len(body) - ((len(body) - start) % 4 == 1)
        data = base64.b64decode(body[start:stop] + "=" * (-(stop - start) % 4))
        if start and packing_of(data) == "zlib":
            yield from _stray(data, 0, "base64")
        yield from _parts(data, "base64")


def _unbase64(layer: Layer) -> Iterator[Layer]:
    """What base64 in the layer decodes to, a piece at a time. Runs that are no text and no stream as they stand are read
    at all alignments."""
    for m in _BASE64.finditer(layer.text):
        found = False
        data = _from_base64(m[0])
        for text, how in _texts(data, "base64") if data is not None else ():
            if text:
                found = True
                yield Layer(text, layer, [0], [(*m.span(), True)], how)
        if not found:
            for text, how in _shifted(m[0]):
                yield Layer(text, layer, [0], [(*m.span(), True)], how)
    if "\n" not in layer.text:
        return
    for spans in _wrapped(layer.text):
        done = set()
        for a, b in spans:
            if a in done:
                continue
            data, found = _from_base64(_BREAK.sub("", layer.text[a:b])), False
            for text, how in _texts(data, "base64") if data is not None else ():
                if text:
                    found = True
                    yield Layer(text, layer, [0], [(a, b, True)], how)
            if found:
                done.add(a)


def _rewrites(layer: Layer) -> Iterator[Layer]:
    if "%" in layer.text and (new := _rewritten(layer, _PERCENT, _percent, "url")):
        yield new
    if ("\\" in layer.text or "&#" in layer.text) and (new := _rewritten(layer, _ESCAPE, _escape, "unicode")):
        yield new


def layers(text: str) -> Iterator[Layer]:
    """The text and all that it unwraps to, until nothing new appears. A text seen before in this
    document, at the same place, ends its branch, so cycles end.

    The worklist holds sources of layers, not layers: the next one is made when it is asked for, so a document
    has one piece of each level in memory, however much it unpacks to."""
    work, seen = [iter([Layer(text)])], set()
    while work:
        layer = next(work[-1], None)
        if layer is None:
            work.pop()
            continue
        where = layer.root_span(0, len(layer.text)) if layer.parent else (0, len(text))
        mark = (where, hashlib.blake2b(layer.text.encode("utf-8", "surrogatepass"), digest_size=16).digest())
        if mark not in seen:
            seen.add(mark)
            yield layer
            work.append(itertools.chain(_rewrites(layer), _unbase64(layer)))


def secrets_in(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, str]]]:
    """Base spans, and all spans (start, end, kind): base ones and those of decoded layers, whose kind
    names the layers, as assign@base64+gzip."""
    base, found = [], set()
    for layer in layers(text):
        spans = scan(layer.text)
        if layer.parent is None:
            base = spans
        else:
            for s, e, k in spans:
                at = layer.root_span(s, e)
                if at is not None:
                    found.add((*at, k, f"{KINDS[k]}@{layer.name}"))
    every = sorted([(s, k, "", e, KINDS[k]) for s, e, k in base] + [(s, k, name, e, name) for s, e, k, name in found])
    return base, [(s, e, name) for s, _, _, e, name in every]


SPANS = "array<struct<kind:string,start:int,end:int>>"


def scan_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, base (spans of the base patterns), spans (all spans).

    Spans are code points of the text, end exclusive. Null texts are empty and have no spans; repeated
    rows are each scanned; extra columns are not read.
    """

    @F.pandas_udf(f"base {SPANS}, spans {SPANS}")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for texts in batches:
            base, every = [], []
            for t in texts:
                b, a = secrets_in(t)
                base.append([{"kind": KINDS[k], "start": s, "end": e} for s, e, k in b])
                every.append([{"kind": n, "start": s, "end": e} for s, e, n in a])
            yield pd.DataFrame({"base": base, "spans": every})

    return docs.select(F.col(id_col).alias("doc_id"), run(F.coalesce(F.col(text_col), F.lit(""))).alias("x")).select("doc_id", "x.base", "x.spans")
