"""Secret scans with a recursive decoding worklist.

A layer is a string whose characters each know the span of the original text they came from. Every layer is scanned;
its encoded stretches (percent-encoding, backslash escapes, base64, and compressed bytes inside) are decoded into new layers on the
worklist until nothing new appears. A layer whose content was already seen on the way is not opened again, so cycles
end, and a layer only opens ones that differ from it.

No layer is dropped for bytes that aren't text: those stand for themselves. Base64 goes on over line breaks and is read at all
four alignments, since a word or path before it belongs to the same letters. Compressed streams are looked for at every place of
decoded bytes, whatever they were decoded from; they are read piece by piece, with an overlap, up to their end or first
error, and what follows them is read as well.
"""

from __future__ import annotations

import base64
import binascii
import bz2
import hashlib
import itertools
import lzma
import re
import zlib
from collections.abc import Callable, Iterator, Sequence

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame

KINDS = ("assign", "access", "hex")
_ASSIGN = re.compile(
    r"""(?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX24 = re.compile(r"[0-9a-f]{24,}")
_URL = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
_BYTES = re.compile(r"(?:\\x[0-9A-Fa-f]{2}){8,}")
_ESCAPE = re.compile(r"(?:\\u[0-9A-Fa-f]{4}|\\u\{[0-9A-Fa-f]{1,6}\}|\\x[0-9A-Fa-f]{2}|\\U[0-9A-Fa-f]{8})")
#: Fewer than 16 letters hold fewer than 12 bytes, and the shortest secret has 12; only a zlib stream, which begins so, may hold more.
_BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}|(?<![A-Za-z0-9+/_-])e[AFJN][A-Za-z0-9+/_-]{9,13}={0,2}")
_MAGIC = re.compile(rb"\x1f\x8b\x08|\x78[\x01\x5e\x9c\xda]|BZh[1-9]1AY&SY|\xfd7zXZ\x00|\x28\xb5\x2f\xfd", re.S)
_WIDE = re.compile(rb"(?:[\x20-\x7e]\x00){12}|(?:\x00[\x20-\x7e]){12}")
_WRAPPED = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]++(?=[ \t\r]*\n)(?:[ \t]*\r?\n[ \t]*[A-Za-z0-9+/_-]++)++={0,2}")
_LINE = re.compile(r"[A-Za-z0-9+/_-]+={0,2}")
#: Bytes of an inflated stream that are one layer, and how much of a layer the next one repeats; an encoded stretch that is longer
#: than the overlap and lies across the end of a layer is opened in two parts.
PIECE, OVERLAP = 64 << 20, 1 << 20


def find(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of one layer, leftmost and non-overlapping in each kind."""
    out = [(m.start(), m.end(), "assign") for m in _ASSIGN.finditer(text) if len(m[1]) >= 6] if "=" in text or ":" in text else []
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in _ACCESS.finditer(text) if len(m[0]) >= 20]
    # a maximal run of 24 and more is what the plain run pattern finds, once short runs are dropped
    return out + [(m.start(), m.end(), "hex") for m in _HEX24.finditer(text)]


def order(spans: set[tuple[int, int, str]] | list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    return sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in spans)


def _maker(head: bytes) -> tuple[Callable, int] | None:
    """What inflates a stream with this magic number, and how many bytes it is fed at a time: a zstd block holds 128 KiB."""
    if head[:2] == b"\x1f\x8b":
        return lambda: zlib.decompressobj(31), 4096
    if head[:1] == b"\x78" and len(head) > 2 and (head[0] * 256 + head[1]) % 31 == 0:
        return zlib.decompressobj, 4096
    if head[:3] == b"BZh":
        return bz2.BZ2Decompressor, 4096
    if head[:6] == b"\xfd7zXZ\x00":
        return lzma.LZMADecompressor, 4096
    if head[:4] == b"\x28\xb5\x2f\xfd":
        return lambda: zstandard.ZstdDecompressor().decompressobj(), 64
    return None


def _fed(one, data: bytes) -> Iterator[bytes]:  # noqa: ANN001
    """Output for some input, a bounded part at a time."""
    if isinstance(one, (bz2.BZ2Decompressor, lzma.LZMADecompressor)):
        yield one.decompress(data, 1 << 20)
        while not one.eof and not one.needs_input:
            yield one.decompress(b"", 1 << 20)
    elif isinstance(one, _ZLIB):
        yield (more := one.decompress(data, 1 << 20))
        while not one.eof and (one.unconsumed_tail or more):
            yield (more := one.decompress(one.unconsumed_tail, 1 << 20))
    else:
        yield one.decompress(data)


def _member(chunks: Iterator[bytes], kind: tuple[Callable, int]) -> Iterator[bytes]:
    """The output of one stream, up to its end or first error."""
    make, step = kind
    one = make()
    for chunk in chunks:
        for at in range(0, len(chunk), step):
            try:
                yield from _fed(one, chunk[at : at + step])
            except _ERRORS:
                return
            if one.eof:
                return


_ZLIB = type(zlib.decompressobj())
_ERRORS = (OSError, EOFError, ValueError, zlib.error, lzma.LZMAError, zstandard.ZstdError)
#: Streams that are read one inside another at once; deeper ones are opened as layers of their own.
_NESTED = 50


def _unpacked(chunks: Iterator[bytes], opened: frozenset[bytes] = frozenset()) -> tuple[Iterator[bytes], bool]:
    """(bytes, whether they were compressed): a stream is inflated, also one that another begins with. A stream that begins like one
    around it is left as it is, so cycles end."""
    head = b""
    for chunk in chunks:
        head += chunk
        if len(head) >= 1024:
            break
    kind = _maker(head)
    chunks = itertools.chain([head], chunks) if head else iter(())
    if kind is None or head[:1024] in opened or len(opened) >= _NESTED:
        return chunks, False
    return _unpacked(_member(chunks, kind), opened | {head[:1024]})[0], True


def _pieces(chunks: Iterator[bytes]) -> Iterator[bytes]:
    held, size, fresh = [], 0, 0
    for chunk in chunks:
        held.append(chunk)
        size, fresh = size + len(chunk), fresh + len(chunk)
        if size >= PIECE:
            whole = b"".join(held)
            yield whole
            held, size, fresh = [whole[-OVERLAP:]], min(OVERLAP, size), 0
    if fresh:
        yield b"".join(held)


def _texts(data: bytes) -> Iterator[tuple[str, int, Callable[[str], int]]]:
    """(text, first byte, bytes of a character) of decoded bytes: UTF-8 in which other bytes stand for themselves, and UTF-16 where
    it could hold a secret, which has 12 characters at least."""
    if data:
        yield data.decode("utf-8", "surrogateescape"), 0, lambda c: 1 if c < "\x80" or "\udc80" <= c <= "\udcff" else len(c.encode())
    if b"\0" in data and _WIDE.search(data):
        for first, code in itertools.product((0, 1), ("utf-16-le", "utf-16-be")):
            even = data[first : len(data) - (len(data) - first) % 2]
            if even:
                yield even.decode(code, "surrogatepass"), first, lambda c: 4 if c > "\uffff" else 2


def _streams(data: bytes) -> Iterator[tuple[int, str]]:
    """(first byte, text of a piece) of what the compressed streams in some bytes hold, wherever they begin; those inside one that
    could be read to its end are part of it."""
    for m in _MAGIC.finditer(data):
        chunks = (data[k : k + (1 << 16)] for k in range(m.start(), len(data), 1 << 16))
        inside, packed = _unpacked(chunks)
        for piece in _pieces(inside) if packed else ():
            for text, _, _ in _texts(piece):
                yield m.start(), text


def _unbase64(token: str) -> bytes | None:
    """The bytes of all whole groups of four, and of a shorter last group unless it is one letter alone."""
    body = token.rstrip("=").replace("-", "+").replace("_", "/")
    body = body[:-1] if len(body) % 4 == 1 else body
    try:
        return base64.b64decode(body + "=" * (-len(body) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def _tokens(text: str) -> Iterator[tuple[str, Sequence[int]]]:
    """(base64, place of each letter): on one line; over line breaks, the whole run, and each stretch of lines of one width with the line behind it."""
    for m in _BASE64.finditer(text):
        yield m[0], range(m.start(), m.end())
    if "\n" not in text:
        return
    for m in _WRAPPED.finditer(text):
        lines = [(x.start(), x.end()) for x in _LINE.finditer(text, m.start(), m.end())]
        starts = [0, *(i for i in range(1, len(lines)) if lines[i][1] - lines[i][0] != lines[i - 1][1] - lines[i - 1][0]), len(lines)]
        parts = {(0, len(lines))} | {(i, min(j + 1, len(lines))) for i, j in itertools.pairwise(starts)}
        for i, j in sorted(parts):
            places = [k for a, b in lines[i:j] for k in range(a, b)] if j - i > 1 else ()
            if len(places) >= 16:
                yield "".join(text[a:b] for a, b in lines[i:j]), places


class _Same:
    """Spans of a layer without places: each character stands for the whole encoded stretch."""

    def __init__(self, n: int, span: tuple[int, int]):
        self.n, self.span = n, span

    def __getitem__(self, at):  # noqa: ANN001
        return [self.span] * len(range(*at.indices(self.n))) if isinstance(at, slice) else self.span


def _runs(text: str, spans: Sequence[tuple[int, int]], pattern: re.Pattern, value: Callable[[str], bytes]) -> Iterator[tuple[bytes, list[tuple[int, int]]]]:
    """(bytes, span of each) of the stretches of escapes that may hold a compressed stream."""
    for m in pattern.finditer(text):
        data = value(m[0])
        if _MAGIC.search(data):
            n = len(m[0]) // len(data)
            yield data, [(spans[k][0], spans[k + n - 1][1]) for k in range(m.start(), m.end(), n)]


def _percent(text: str, spans: Sequence[tuple[int, int]]) -> tuple[str, list[tuple[int, int]]] | None:
    out, where, at, changed = [], [], 0, False
    for m in _URL.finditer(text):
        data = bytes.fromhex(m[0].replace("%", ""))
        piece = data.decode("utf-8", "surrogateescape")
        out.append(text[at : m.start()])
        where += spans[at : m.start()]
        pos = m.start()
        for c in piece:
            n = 3 * (1 if "\udc80" <= c <= "\udcff" else len(c.encode()))
            where.append((spans[pos][0], spans[pos + n - 1][1]))
            pos += n
        out.append(piece)
        at, changed = m.end(), True
    return ("".join(out) + text[at:], where + spans[at:]) if changed else None


def _escapes(text: str, spans: Sequence[tuple[int, int]]) -> tuple[str, list[tuple[int, int]]] | None:
    out, where, at = [], [], 0
    for m in _ESCAPE.finditer(text):
        code = int(re.sub(r"[^0-9A-Fa-f]", "", m[0][2:]), 16)
        if code > 0x10FFFF or 0xD800 <= code <= 0xDFFF and m[0][1] != "u":
            continue
        out += [text[at : m.start()], chr(code)]
        where += [*spans[at : m.start()], (spans[m.start()][0], spans[m.end() - 1][1])]
        at = m.end()
    if not at:
        return None
    whole, where = "".join(out) + text[at:], where + spans[at:]
    if re.search("[\ud800-\udfff]", whole):  # two escapes may make one character
        joined_, places, i = [], [], 0
        while i < len(whole):
            if "\ud800" <= whole[i] <= "\udbff" and i + 1 < len(whole) and "\udc00" <= whole[i + 1] <= "\udfff":
                joined_.append(chr(0x10000 + ((ord(whole[i]) - 0xD800) << 10) + ord(whole[i + 1]) - 0xDC00))
                places.append((where[i][0], where[i + 1][1]))
                i += 2
            else:
                joined_.append("\ufffd" if "\ud800" <= whole[i] <= "\udfff" else whole[i])
                places.append(where[i])
                i += 1
        whole, where = "".join(joined_), places
    return whole, where


def _opened(text: str, spans: Sequence[tuple[int, int]]) -> Iterator[tuple[str, Sequence[tuple[int, int]]]]:
    """The layers directly inside one."""
    if "%" in text:
        if got := _percent(text, spans):
            yield got
        for data, where in _runs(text, spans, _URL, lambda x: bytes.fromhex(x.replace("%", ""))):
            yield from ((inner, _Same(len(inner), (where[at][0], where[-1][1]))) for at, inner in _streams(data))
    if "\\" in text:
        if got := _escapes(text, spans):
            yield got
        for data, where in _runs(text, spans, _BYTES, lambda x: bytes.fromhex(x.replace("\\x", ""))):
            yield from ((inner, _Same(len(inner), (where[at][0], where[-1][1]))) for at, inner in _streams(data))
    if isinstance(spans, _Same):  # what a stream held may hold others
        yield from ((inner, _Same(len(inner), spans.span)) for _, inner in _streams(text.encode("utf-8", "surrogateescape")) if inner)
    for token, places in _tokens(text):
        for first in range(4):
            data = _unbase64(token[first:])
            if not data:
                continue
            for at, inner in _streams(data):  # a compressed stream has no place for each character
                yield inner, _Same(len(inner), (spans[places[first + at * 8 // 6]][0], spans[places[-1]][1]))
            for inner, at, width in _texts(data):
                where, last = [], len(places) - 1
                for c in inner:
                    n = width(c)
                    where.append((spans[places[first + at * 8 // 6]][0], spans[places[min(last, first + ((at + n) * 8 - 1) // 6)]][1]))
                    at += n
                yield inner, where


def _may_open(text: str) -> bool:
    return "%" in text and bool(_URL.search(text)) or "\\" in text and bool(_ESCAPE.search(text)) or bool(_BASE64.search(text)) or "\n" in text and bool(_WRAPPED.search(text))


class _Whole:
    """Spans of the original text: each character stands for itself."""

    def __init__(self, n: int):
        self.n = n

    def __getitem__(self, at):  # noqa: ANN001
        return [(i, i + 1) for i in range(*at.indices(self.n))] if isinstance(at, slice) else (at, at + 1)


def scan(text: str) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """(base spans, all spans) of a text, ordered; spans of inner layers are mapped to the text."""
    base = order(find(text))
    if not _may_open(text):
        return base, base
    found, seen = set(base), {hashlib.sha256(text.encode("utf-8", "surrogatepass")).digest()}
    work = [(text, _opened(text, _Whole(len(text))))]  # depth first, so one piece of each stream is held
    while work:
        layer, inside = work[-1]
        inner, where = next(inside, (None, None))
        if inner is None:
            work.pop()
            continue
        mark = hashlib.sha256(repr(where[:1] + where[-1:]).encode() + inner.encode("utf-8", "surrogatepass")).digest()
        if mark in seen or inner == layer:
            continue
        seen.add(mark)
        for start, end, kind in find(inner):
            found.add((where[start][0], where[end - 1][1], kind))
        if _may_open(inner):
            work.append((inner, _opened(inner, where)))
    return base, order(found)


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"


def scan_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: base counts by kind, the SHA-256 of the joined base spans, and all spans joined.

    Narrow: no shuffle. A null text counts as empty and has no spans; ids may be null or repeat; other columns are
    ignored; an empty table gives no rows. Whole texts are scanned, whatever their length.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for text in batch.column(1):
                base, full = scan(text.as_py() or "")
                n = [sum(k == kind for _, _, k in base) for kind in KINDS]
                rows.append((*n, hashlib.sha256(joined(base).encode()).hexdigest(), joined(full)))
            cols = list(zip(*rows, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), *(pa.array(c, pa.int64()) for c in cols[:3]), *(pa.array(c, pa.string()) for c in cols[3:])],
                ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
            )

    return docs.select(id_col, text_col).mapInArrow(run, SCHEMA)
