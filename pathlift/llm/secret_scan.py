"""Secret scanning through nested encodings.

Base patterns run over the text itself.  A worklist then unwraps every encoded
stretch (percent escapes, Unicode escapes, base64, compressed bytes), scans what
came out, maps each finding back to the characters of the original text that carry
it, and unwraps the new layer in turn until nothing new appears.  Layers already
seen (by digest) are not unwrapped again, so cycles end.

Nothing is asked of what a stretch decodes to: bytes that are no UTF-8 and characters
that are not printable stay in the layer, and the patterns are looked for around them.
Base64 runs are decoded from each of their first four characters, since a word may be
glued to them, and once more with wrapped lines joined.  Compressed bytes count wherever
their magic number stands, with all their members, however often they are compressed.
"""

from __future__ import annotations

import base64
import binascii
import bz2
import codecs
import hashlib
import lzma
import re
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .frames import add_columns, fresh

# The kinds in their order, and the base patterns.
KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
ASSIGN_LENGTH = 12
_ASSIGN_HINTS = ("passw", "secret", "token", "api")

PERCENT = re.compile(r"%[0-9A-Fa-f]{2}")
ESCAPE = re.compile(r"\\u\{([0-9A-Fa-f]{1,6})\}|\\u([0-9A-Fa-f]{4})|\\x([0-9A-Fa-f]{2})")
BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
WRAPPED = re.compile(r"[A-Za-z0-9+/_-]+(?:\r?\n[\x20\t]*[A-Za-z0-9+/_-]+)+={0,2}")
MAGIC = re.compile(rb"\x1f\x8b\x08|\x78[\x01\x5e\x9c\xda]|BZh[1-9]|\xfd7zXZ\x00|\x28\xb5\x2f\xfd", re.DOTALL)
# What no pattern and no encoding runs across: a character of none of them, or a blank between words.
BREAK = re.compile(r"""[^A-Za-z0-9+/_.=%\\{}:"'\x20\t\r\n-]|(?<=[A-Za-z0-9])\x20(?=[A-Za-z0-9])""")
PIECE = 1 << 20


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the base patterns, leftmost and non-overlapping per kind."""
    out = []
    low = text.lower()
    if any(h in low for h in _ASSIGN_HINTS):
        out += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LENGTH]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text)]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return out


@dataclass
class Layer:
    """Decoded text with, for each of its characters, the original span it stems from.

    ``marks`` is None for the original itself, a pair for a layer that maps as a
    whole, or (starts, ends) lists by character.
    """

    text: str
    marks: tuple | None = None

    def outer(self, start: int, end: int) -> tuple[int, int]:
        if self.marks is None:
            return start, end
        a, b = self.marks
        if isinstance(a, int):
            return a, b
        return a[start], b[end - 1]


def _stretches(text: str, needle: re.Pattern, ends: str):
    """Spans between delimiter characters around the matches of a needle, left to right."""
    done = 0
    for m in needle.finditer(text):
        if m.start() >= done:
            start = max(done, *(text.rfind(c, done, m.start()) + 1 for c in ends))
            stops = [k for k in (text.find(c, m.end()) for c in ends) if k >= 0]
            done = min(stops, default=len(text))
            yield start, done


def _decompressor(head: bytes):
    if head[:2] == b"\x1f\x8b":
        return zlib.decompressobj(31)
    if head[:1] == b"\x78" and len(head) > 2 and int.from_bytes(head[:2], "big") % 31 == 0:
        return zlib.decompressobj(15)
    if head[:3] == b"BZh":
        return bz2.BZ2Decompressor()
    if head[:6] == b"\xfd7zXZ\x00":
        return lzma.LZMADecompressor()
    if head[:4] == b"\x28\xb5\x2f\xfd":
        return zstandard.ZstdDecompressor().decompressobj()
    return None


def _step(unpack, data: bytes) -> tuple[bytes, bytes, bool]:
    """(content, data still to be fed, whether more content may come without data)."""
    if isinstance(unpack, bz2.BZ2Decompressor | lzma.LZMADecompressor):
        piece = unpack.decompress(data, PIECE)
        return piece, b"", not unpack.eof and not unpack.needs_input
    if type(unpack).__module__.startswith("zstandard"):  # it takes no limit: a few bytes at a time
        return unpack.decompress(data[:256]), data[256:], False
    piece = unpack.decompress(data, PIECE)
    return piece, unpack.unconsumed_tail, len(piece) == PIECE


def _members(chunks: Iterator[bytes]) -> Iterator[tuple[int, bytes]]:
    """(member, piece of its content) of compressed bytes, up to where they are damaged; what follows the last member as it is."""
    data, member = b"", -1
    while True:
        while len(data) < 6 and (more := next(chunks, None)) is not None:
            data += more
        data = data.lstrip(b"\0") if member >= 0 else data
        unpack = _decompressor(data)
        member += 1
        if unpack is None:
            if member:
                if data:
                    yield member, data
                yield from ((member, c) for c in chunks)
            return
        more = False
        try:
            while not unpack.eof:
                if not data and not more:
                    data = next(chunks, None)
                    if data is None:
                        return
                piece, data, more = _step(unpack, data)
                if piece:
                    yield member, piece
        except (zlib.error, OSError, ValueError, lzma.LZMAError, zstandard.ZstdError, EOFError):
            return
        data = unpack.unused_data + data


def _windows(pieces: Iterator[bytes], most: int) -> Iterator[str]:
    """The text of bytes in windows of about ``most`` characters, cut where no secret can be cut."""
    decoder = codecs.getincrementaldecoder("utf-8")("replace")
    held, size, limit = [], 0, most
    for piece in pieces:
        held.append(decoder.decode(piece))
        size += len(held[-1])
        if size >= limit:
            text = "".join(held)
            cut = BREAK.search(text[::-1])
            if cut:
                yield text[: len(text) - cut.start()]
                text = text[len(text) - cut.start() :]
            held, size, limit = [text], len(text), max(most, 2 * len(text))
    yield "".join([*held, decoder.decode(b"", True)])


def _unpacked(raw: bytes, most: int) -> Iterator[str]:
    """Text windows of all that compressed bytes hold, and of what that holds compressed, and so on."""
    todo: list[Callable[[], Iterator[bytes]]] = [lambda: iter([raw])]
    seen = {hashlib.sha1(raw).digest()}
    while todo:
        stream = todo.pop()
        digest, heads, kept, size = hashlib.sha1(), {}, [], 0

        def content(member: int | None = None, stream=stream) -> Iterator[bytes]:
            return (p for k, p in _members(stream()) if member is None or k == member)

        def noted(stream=stream, digest=digest, heads=heads, kept=kept) -> Iterator[bytes]:
            nonlocal size
            for k, p in _members(stream()):
                digest.update(p)
                heads[k] = (heads.get(k, b"") + p[:6])[:6]
                size += len(p)
                if size <= most:
                    kept.append((k, p))
                else:
                    kept.clear()
                yield p

        yield from _windows(noted(), most)
        if not size or digest.digest() in seen:
            continue
        seen.add(digest.digest())
        for k, head in heads.items():
            if _decompressor(head) is not None:
                # all members together when the first is compressed, and each later one by itself
                if size > most:
                    todo.append(lambda k=k, content=content: content(k or None))
                else:
                    inner = b"".join(p for j, p in kept if k in (0, j))
                    todo.append(lambda inner=inner: iter([inner]))


def _percent(text: str) -> tuple[str, list[int], list[int]]:
    """Percent-decoded text with the start and end of each character's source."""
    chars, starts, ends, at = [], [], [], 0
    while at < len(text):
        run = at
        raw = bytearray()
        while text[run : run + 1] == "%" and re.fullmatch("[0-9A-Fa-f]{2}", text[run + 1 : run + 3]):
            raw.append(int(text[run + 1 : run + 3], 16))
            run += 3
        if not raw:
            chars.append(text[at])
            starts.append(at)
            ends.append(at + 1)
            at += 1
            continue
        for c in raw.decode("utf-8", "replace"):
            width = 3 * (1 if c == "\ufffd" else len(c.encode()))
            chars.append(c)
            starts.append(min(at, run - 3))
            ends.append(min(at + width, run))
            at += width
        at = run
    return "".join(chars), starts, ends


def _escaped(text: str) -> tuple[str, list[int], list[int]]:
    chars, starts, ends, at = [], [], [], 0
    for m in ESCAPE.finditer(text):
        for k in range(at, m.start()):
            chars.append(text[k])
            starts.append(k)
            ends.append(k + 1)
        code = int(m[1] or m[2] or m[3], 16)
        low = chars and 0xD800 <= ord(chars[-1]) < 0xDC00 and 0xDC00 <= code < 0xE000
        if low:  # a surrogate pair makes one character
            chars[-1] = chr(0x10000 + ((ord(chars[-1]) - 0xD800) << 10) + code - 0xDC00)
            ends[-1] = m.end()
        else:
            chars.append(chr(code) if code < 0x110000 else "\ufffd")
            starts.append(m.start())
            ends.append(m.end())
        at = m.end()
    for k in range(at, len(text)):
        chars.append(text[k])
        starts.append(k)
        ends.append(k + 1)
    return "".join(chars), starts, ends


def _ends(raw: bytes, text: str) -> list[int]:
    """Where in the bytes each character of their text ends; undecodable bytes are lone surrogates."""
    if len(text) == len(raw):
        return list(range(1, len(raw) + 1))
    out, at = [], 0
    for c in text:
        at += 1 if c < "\x80" or "\udc80" <= c <= "\udcff" else len(c.encode())
        out.append(at)
    return out


def _holds(text: str) -> bool:
    """Whether a decoded text has a secret or something to unwrap."""
    return "%" in text or "\\" in text or bool(BASE64.search(text) or WRAPPED.search(text) or base_spans(text))


def _inner_layers(layer: Layer, most: int) -> Iterator[Layer]:
    """What the encoded stretches of a layer decode to."""
    text = layer.text

    def by_char(decoded: str, starts: list[int], ends: list[int]) -> Layer:
        spans = [layer.outer(a, b) for a, b in zip(starts, ends, strict=True)]
        return Layer(decoded, ([a for a, _ in spans], [b for _, b in spans]))

    for sign, needle, ends, decode in (("%", PERCENT, " \t\r\n\"'<>", _percent), ("\\", ESCAPE, " \t\r\n", _escaped)):
        if sign in text:
            for a, b in _stretches(text, needle, ends):
                decoded, froms, tos = decode(text[a:b])
                yield by_char(decoded, [a + k for k in froms], [a + k for k in tos])

    runs = [(m, False) for m in BASE64.finditer(text)]
    if "\n" in text:
        runs += [(m, True) for m in WRAPPED.finditer(text) if len(m[0]) >= 16]
    for m, wrapped in runs:
        run = re.sub(r"\s", "", m[0]) if wrapped else m[0]
        body = run.rstrip("=").translate({45: 43, 95: 47})
        for first in range(4):
            size = len(body) - first
            size -= size % 4 == 1
            if size < 2:
                continue
            raw = base64.b64decode(body[first : first + size] + "=" * (-size % 4))
            plain = raw.decode("utf-8", "surrogateescape")
            if _holds(plain):
                if not plain.isascii() and first == 0 and not wrapped and not any("\udc80" <= c <= "\udcff" for c in plain):
                    yield Layer(plain, layer.outer(m.start(), m.end()))
                else:  # byte k of the content lies in the group of four characters around 4k/3
                    at = [k for k in range(m.start(), m.end()) if text[k] not in "\r\n\t "] if wrapped else range(m.start(), m.end())
                    tos = _ends(raw, plain)
                    froms = [0, *tos[:-1]]
                    group = lambda k: first + 4 * (k // 3)  # noqa: B023, E731
                    yield by_char(plain, [at[group(a)] for a in froms], [at[min(group(b - 1) + 3, len(run) - 1)] + 1 for b in tos])
            for magic in MAGIC.finditer(raw):
                for window in _unpacked(raw[magic.start() :], most):
                    yield Layer(window, layer.outer(m.start(), m.end()))


def scan(text: str | None, max_layer_bytes: int = 1 << 24) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """(base spans, all spans), each sorted by start and then by kind.

    Null and empty texts have none.  Compressed content is scanned in windows of about
    ``max_layer_bytes``; a window grows only where an encoding may run on.
    """
    text = text or ""
    key = lambda s: (s[0], KINDS.index(s[2]), s[1])
    base = sorted(base_spans(text), key=key)
    found, seen = set(base), {hashlib.sha1(text.encode("utf-8", "surrogatepass")).digest()}
    work = [_inner_layers(Layer(text), max_layer_bytes)]
    while work:
        inner = next(work[-1], None)
        if inner is None:
            work.pop()
        elif inner.text:
            digest = hashlib.sha1(inner.text.encode("utf-8", "surrogatepass") + repr(inner.outer(0, len(inner.text))).encode()).digest()
            if digest not in seen:
                seen.add(digest)
                found |= {(*inner.outer(a, b), kind) for a, b, kind in base_spans(inner.text)}
                work.append(_inner_layers(inner, max_layer_bytes))
    return base, sorted(found, key=key)


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


def redact(text: str, spans: list[tuple[int, int, str]], mark: str = "[secret]") -> str:
    """The text with every span (overlapping ones together) replaced by a mark."""
    out, at = [], 0
    for a, b, _ in sorted(spans):
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join([*out, text[at:]])


def scan_secrets(df: DataFrame, text_col: str = "text", *, redacted_col: str | None = None, max_layer_bytes: int = 1 << 24) -> DataFrame:
    """Adds n_assign, n_access, n_hex (base matches by kind), base_spans and spans.

    Null texts count as empty: zero counts and empty strings.  ``redacted_col``
    also returns the text with every span replaced (null stays null).  Columns of
    the output names are replaced, others kept; repeated rows are scanned alike.  Of
    spans that overlap all are listed, sorted by start, kind and end; texts of any
    length are scanned whole; an empty table stays empty.
    """
    fields = [*[(f"n_{k}", T.LongType()) for k in KINDS], ("base_spans", T.StringType()), ("spans", T.StringType())]
    if redacted_col and redacted_col.lower() == text_col.lower():
        # the text itself is replaced: carry it under another name meanwhile
        (meanwhile,) = fresh(df, "redacted")
        moved = scan_secrets(df, text_col, redacted_col=meanwhile, max_layer_bytes=max_layer_bytes)
        return moved.drop(text_col).withColumnRenamed(meanwhile, text_col)
    if redacted_col:
        fields.append((redacted_col, T.StringType()))

    def make(batch: pa.RecordBatch) -> list:
        texts = [x.as_py() for x in batch.column(batch.schema.names.index(text_col))]
        found = [scan(x, max_layer_bytes) for x in texts]
        out = [pa.array([sum(s[2] == k for s in base) for base, _ in found], pa.int64()) for k in KINDS]
        out += [pa.array([joined(f[i]) for f in found], pa.string()) for i in (0, 1)]
        if redacted_col:
            out.append(pa.array([None if x is None else redact(x, f[1]) for x, f in zip(texts, found, strict=True)], pa.string()))
        return out

    return add_columns(df, fields, make)
