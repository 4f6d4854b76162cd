"""Secret scans through nested encodings: a worklist of decoded layers, run to a fixpoint.

The text itself is the first layer. Every layer is scanned for secrets, and every encoded
stretch in it becomes a further layer: lines with URL escapes, lines with Unicode escapes,
base64 runs (standard or URL alphabet, also wrapped in lines of 64 or 76), and gzip, zlib or bzip2
data below base64. A layer seen before at the same place is not taken up again, which ends cycles; equal layers
of other places are. The worklist ends when no new layer appears. A layer knows by runs where its characters
came from in the layer above: a run is a stretch of characters that each stand for equally much of it. A finding inside any
depth of wrapping is traced up through the runs and reported as a span of the original text. Findings in the
text itself always stay.

Defined results: null and empty texts have no spans; repeated rows each give a row; equal spans of one
kind found through several layers count once; a null doc_id stays null; other columns are
ignored. Unescaped lines and inflated data are scanned in pieces of about `PIECE` characters, so that a worker holds
one of them at a time; compressed data is inflated to its end, member after member. Pieces end where no pattern can reach
across; a longer stretch without such a place stays whole. Broken data is scanned up to the break, and what follows the
last member as it stands.
"""

from __future__ import annotations

import binascii
import bz2
import codecs
import hashlib
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, row_schema, texts

KINDS = ("assign", "access", "hex")
PIECE = 1 << 18
REDACTED = "[SECRET]"

# The patterns and least lengths of the base scan.
_ASSIGN = re.compile(
    r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE
)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{16,}")
ASSIGN_LENGTH, ACCESS_LENGTH, HEX_LENGTH = 12, 18, 16

#: Cheap tests on bytes that tell whether a pattern can match at all.
_WORDS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
_AS_HEX = bytes(0x68 if chr(b) in "0123456789abcdef" else 0x20 for b in range(256))
_HEX_RUN = b"h" * HEX_LENGTH

_URL_ESCAPE = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
_UNICODE_ESCAPE = re.compile(r"(?:\\u\{[0-9A-Fa-f]{1,6}\}|\\u[0-9A-Fa-f]{4}|\\U[0-9A-Fa-f]{8}|\\x[0-9A-Fa-f]{2})+")
_ONE_ESCAPE = re.compile(r"\\u\{([0-9A-Fa-f]+)\}|\\u([0-9A-Fa-f]{4})|\\U([0-9A-Fa-f]{8})|\\x([0-9A-Fa-f]{2})")
_BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
_WRAPPED = re.compile(r"(?:^|(?<=[^A-Za-z0-9+/]))[A-Za-z0-9+/]{64}(?:[A-Za-z0-9+/]{12})?\r?\n(?:[A-Za-z0-9+/]+\r?\n)*[A-Za-z0-9+/]*={0,2}")
_LINE = re.compile(r"[^\r\n]+")
_CONTROL = re.compile(rb"[\x00-\x08\x0b\x0c\x0e-\x1f\x7f]")
_URL_SAFE = str.maketrans("-_", "+/")
#: Up to the last character that no pattern holds, or the last line break that no wrapped run holds.
_UP_TO_CUT = re.compile(r"""(?s:.*)(?:[^A-Za-z0-9+/_.=\x20"':\\{}%\r\n-]|(?<=[^A-Za-z0-9+/\r])\n)""")


#: Runs are rows (at, src, off, p, q): character at + j stands for the characters src + (off + j p) / q, rounded down, up to
#: src + (off + (j + 1) p) / q, rounded up, of the layer above.
_RUN = np.int64


def _run(*row: int) -> np.ndarray:
    return np.array([row], _RUN)


def _cut_runs(runs: np.ndarray, a: int, b: int) -> np.ndarray:
    """The runs of characters a .. b-1, numbered from a."""
    first = int(np.searchsorted(runs[:, 0], a, side="right")) - 1
    out = runs[first : int(np.searchsorted(runs[:, 0], b, side="left"))].copy()
    out[0, 2] += (a - out[0, 0]) * out[0, 3]
    out[:, 0] = np.maximum(out[:, 0] - a, 0)
    return out


@dataclass(frozen=True, eq=False)
class Layer:
    """A decoded text and the layer that it came from.

    `span`: the original range of every character alike. `later`: a further piece of a layer already counted.
    """

    text: str
    above: Layer | None = None
    runs: np.ndarray | None = None
    span: tuple[int, int] | None = None
    depth: int = 0
    later: bool = False

    def bounds(self, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Original start of the characters `first`, and original end of the characters `last`."""
        if self.span is not None:
            return np.full(len(first), self.span[0], _RUN), np.full(len(last), self.span[1], _RUN)
        if self.above is None:
            return first, last + 1
        at, src, off, p, q = self.runs.T
        k = np.searchsorted(at, first, side="right") - 1
        begin = src[k] + (off[k] + (first - at[k]) * p[k]) // q[k]
        k = np.searchsorted(at, last, side="right") - 1
        end = src[k] - -(off[k] + (last - at[k] + 1) * p[k]) // q[k]
        return self.above.bounds(begin, end - 1)

    def original(self, a: int, b: int) -> tuple[int, int]:
        if self.span is not None:
            return self.span
        if self.above is None:
            return a, b
        begin, end = self.bounds(np.array([a], _RUN), np.array([b - 1], _RUN))
        return int(begin[0]), int(end[0])

    def child(self, text: str, runs: np.ndarray, later: bool = False) -> Layer:
        return Layer(text, self, runs, self.span, self.depth + 1, later)

    def piece(self, text: str, a: int, b: int, later: bool) -> Layer:
        """All of `text` came from one range of this layer."""
        return Layer(text, self, None, self.original(a, b), self.depth + 1, later)

    def key(self) -> bytes:
        """A digest of the text and the original range of each of its characters."""
        digest = hashlib.blake2b(b"%d:" % len(self.text), digest_size=16)
        for i in range(0, len(self.text), 1 << 16):
            digest.update(self.text[i : i + (1 << 16)].encode("utf-8", "surrogatepass"))
        if self.span is not None:
            digest.update(b"%d:%d" % self.span)
            return digest.digest()
        for i in range(0, len(self.text), 1 << 16):
            at = np.arange(i, min(len(self.text), i + (1 << 16)))
            for x in self.bounds(at, at):
                digest.update(x.tobytes())
        return digest.digest()


def base_spans(text: str) -> list[tuple[int, str, int]]:
    """(start, kind, end) of what one text shows, leftmost and non-overlapping per kind."""
    raw = text.encode("utf-8", "replace")
    low, out = raw.lower(), []
    if any(w in low for w in _WORDS):
        out += [(m.start(), "assign", m.end()) for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LENGTH]
    if b"AKIA" in raw:
        out += [(m.start(), "access", m.end()) for m in _ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LENGTH]
    if _HEX_RUN in raw.translate(_AS_HEX):
        out += [(m.start(), "hex", m.end()) for m in _HEX.finditer(text)]
    return out


def _lines_with(pattern: re.Pattern, text: str) -> Iterator[tuple[int, int]]:
    at = 0
    while m := pattern.search(text, at):
        a = text.rfind("\n", 0, m.start()) + 1
        b = text.find("\n", m.end())
        b = len(text) if b < 0 else b
        yield a, b
        at = b + 1
        if at > len(text):
            return


def _utf8_runs(data: bytes, src: int, p: int, q: int) -> tuple[str, np.ndarray] | None:
    """Decoded text and its runs, where each byte stands for p / q characters from `src` on; None if not UTF-8."""
    try:
        text = data.decode()
    except UnicodeDecodeError:
        return None
    if len(text) == len(data):
        return text, _run(0, src, 0, p, q)
    lead = np.flatnonzero((np.frombuffer(data, np.uint8) & 0xC0) != 0x80)  # first byte of each character
    width = np.diff(lead, append=len(data))
    at = np.flatnonzero(np.diff(width, prepend=0))
    return text, np.stack([at, np.full(len(at), src), lead[at] * p, width[at] * p, np.full(len(at), q)], axis=1).astype(_RUN)


def _unescaped(layer: Layer, pattern: re.Pattern, decode) -> Iterator[Layer]:
    for a, b in _lines_with(pattern, layer.text):
        later = False
        for text, runs in _pieces(_tokens(layer.text, a, b, pattern, decode)):
            yield layer.child(text, runs, later)
            later = True


def _tokens(text: str, a: int, b: int, pattern: re.Pattern, decode) -> Iterator[tuple[str, list]]:
    """What a line holds, plain and decoded by turns: short texts and the rows of their runs."""
    at = a
    for m in pattern.finditer(text, a, b):
        found = decode(m.group(), m.start())
        if found is None:
            continue
        yield from _plain(text, at, m.start())
        decoded, runs = found
        if len(decoded) <= PIECE:
            yield decoded, runs.tolist()
        else:
            for i in range(0, len(decoded), PIECE):
                yield decoded[i : i + PIECE], _cut_runs(runs, i, i + PIECE).tolist()
        at = m.end()
    yield from _plain(text, at, b)


def _plain(text: str, a: int, b: int) -> Iterator[tuple[str, list]]:
    for i in range(a, b, PIECE):
        yield text[i : min(b, i + PIECE)], [(0, i, 0, 1, 1)]


def _pieces(tokens: Iterator[tuple[str, list]]) -> Iterator[tuple[str, np.ndarray]]:
    """Texts and runs of about `PIECE` characters, cut where no pattern can reach across; at least one."""
    held: list[str] = []
    rows: list[tuple[int, ...]] = []
    size, any_cut = 0, False

    def add(text: str, own: list) -> None:
        nonlocal size
        held.append(text)
        rows.extend((at + size, src, off, p, q) for at, src, off, p, q in own)
        size += len(text)

    def whole() -> tuple[str, np.ndarray]:
        return "".join(held), np.array(rows or [(0, 0, 0, 1, 1)], _RUN)

    for text, own in tokens:
        if size + len(text) >= PIECE and (cut := _UP_TO_CUT.match(text)):
            runs, at = np.array(own, _RUN), cut.end()
            add(text[:at], _cut_runs(runs, 0, at).tolist())
            yield whole()
            held, rows, size, any_cut = [], [], 0, True
            if at == len(text):
                continue
            text, own = text[at:], _cut_runs(runs, at, len(text)).tolist()
        add(text, own)
    if held or not any_cut:
        yield whole()


def _url(escape: str, at: int):
    return _utf8_runs(bytes.fromhex(escape.replace("%", "")), at, 3, 1)


def _unicode(escape: str, at: int):
    text, rows = [], []
    for m in _ONE_ESCAPE.finditer(escape):
        code = int(next(g for g in m.groups() if g), 16)
        if code > 0x10FFFF:
            return None
        if 0xDC00 <= code <= 0xDFFF and text and 0xD800 <= ord(text[-1]) <= 0xDBFF:  # the second half of a pair
            text[-1] = chr(0x10000 + ((ord(text[-1]) - 0xD800) << 10) + code - 0xDC00)
            if rows[-1][0] == len(text) - 1:
                rows[-1][3] += m.end() - m.start()
            else:
                before = rows[-1][1] + rows[-1][3] * (len(text) - 1 - rows[-1][0])
                rows.append([len(text) - 1, before, 0, at + m.end() - before, 1])
            continue
        width = m.end() - m.start()
        if not rows or rows[-1][3] != width or rows[-1][1] + width * (len(text) - rows[-1][0]) != at + m.start():
            rows.append([len(text), at + m.start(), 0, width, 1])
        text.append(chr(code))
    return "".join(text), np.array(rows, _RUN)


def _decompressor(data: bytes):
    """For data that begins as gzip, zlib or bzip2 does; None for other data."""
    if data[:2] == b"\x1f\x8b" or data[:1] == b"\x78" and len(data) > 2 and (data[0] << 8 | data[1]) % 31 == 0:
        return zlib.decompressobj(47)
    return bz2.BZ2Decompressor() if data[:3] == b"BZh" else None


def _inflated(data: bytes) -> Iterator[bytes]:
    """What all members hold, at most `PIECE` bytes at a time, and what follows them; raises where data is broken."""
    while (member := _decompressor(data)) is not None:
        while not member.eof:
            out = member.decompress(data, PIECE)
            data = member.unconsumed_tail if hasattr(member, "unconsumed_tail") else b""
            if out:
                yield out
            elif not data and not member.eof:  # the data ends inside a member
                return
        data = member.unused_data.lstrip(b"\0")
    if data:
        yield data


def _text_pieces(parts: Iterator[bytes]) -> Iterator[str]:
    """The parts as text, cut where no pattern can reach across; at least one piece."""
    decoder, held, size, any_cut = codecs.getincrementaldecoder("utf-8")("replace"), [], 0, False
    for part in parts:
        text = decoder.decode(part)
        size += len(text)
        if size >= PIECE and (cut := _UP_TO_CUT.match(text)):
            yield "".join([*held, cut.group()])
            text = text[cut.end() :]
            held, size, any_cut = [], len(text), True
        held.append(text)
    rest = "".join([*held, decoder.decode(b"", True)])
    if rest or not any_cut:
        yield rest


def _compressed(layer: Layer, data: bytes, a: int, b: int) -> Iterator[Layer]:
    """Layers of compressed data that came from one range; returns whether it was such, and unbroken."""
    if _decompressor(data) is None:
        return False
    broken = False

    def parts() -> Iterator[bytes]:
        nonlocal broken
        try:
            yield from _inflated(data)
        except (zlib.error, OSError, EOFError, ValueError):
            broken = True

    later = False
    for text in _text_pieces(parts()):
        if text or not broken:
            yield layer.piece(text, a, b, later)
            later = True
    return not broken


def _from_base64(layer: Layer, run: str, place: int) -> Iterator[Layer]:
    """Layers of one run; `place`: where it begins in the layer."""
    plain = run.translate(_URL_SAFE) if "-" in run or "_" in run else run
    plain = plain.rstrip("=")
    for off in range(4):  # the run may begin with characters that are not part of it
        body = plain[off:] if off else plain
        extra = len(body) % 4
        if extra == 1:
            body = body[:-1]
        try:
            data = binascii.a2b_base64(body + "=" * (-len(body) % 4))
        except (binascii.Error, ValueError):
            continue
        if len(data) < 8:
            return
        if (yield from _compressed(layer, data, place + off, place + off + len(body))):
            return
        if _CONTROL.search(data):
            continue
        found = _utf8_runs(data, place + off, 4, 3)
        if found is not None:
            yield layer.child(*found)
            return


def decoded_layers(layer: Layer) -> Iterator[Layer]:
    """The layers one step below this one."""
    text = layer.text
    if "%" in text:
        yield from _unescaped(layer, _URL_ESCAPE, _url)
    if "\\" in text:
        yield from _unescaped(layer, _UNICODE_ESCAPE, _unicode)
    for m in _BASE64.finditer(text):
        run, any_found = m.group(), False
        for at in dict.fromkeys((0, run.find("/") + 1, run.rfind("/") + 1)):  # data may follow a path
            if len(run) - at >= 16 and not any_found:
                for below in _from_base64(layer, run[at:], m.start() + at):
                    any_found = True
                    yield below
    if len(text) > 64 and "\n" in text:
        for m in _WRAPPED.finditer(text):
            lines, rows, n = [], [], 0
            for line in _LINE.finditer(text, m.start(), m.end()):
                lines.append(line.group())
                rows.append((n, line.start(), 0, 1, 1))
                n += len(lines[-1])
            joined = layer.child("".join(lines), np.array(rows, _RUN))
            yield from _from_base64(joined, joined.text, 0)


def scan(text: str) -> tuple[list[tuple[int, str, int]], list[tuple[int, str, int]], int]:
    """Base spans, all spans (each sorted), and the number of layers looked at."""
    first = Layer(text)
    base = sorted(set(base_spans(text)), key=_order)
    found, seen, work, layers = set(base), set(), [decoded_layers(first)], 1
    while work:
        below = next(work[-1], None)
        if below is None:
            work.pop()
            continue
        if not seen:
            seen.add(first.key())
        key = below.key()
        if key in seen:
            continue
        seen.add(key)
        layers += not below.later
        work.append(decoded_layers(below))
        for a, kind, b in base_spans(below.text):
            start, end = below.original(a, b)
            found.add((start, kind, end))
    return base, sorted(found, key=_order), layers


def _order(span: tuple[int, str, int]) -> tuple:
    return span[0], KINDS.index(span[1]), span[2]


def redact(text: str, spans: list[tuple[int, str, int]], mark: str = REDACTED) -> str:
    """The text with every span, joined where they overlap, replaced by the mark."""
    out, at = [], 0
    for start, _, end in spans:
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join([*out, text[at:]]) if out else text


_SPAN = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())])
_SPAN_SQL = "array<struct<kind: string, start: long, `end`: long>>"


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, base_spans, spans (arrays of kind, start, end), layers, for every row."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [scan(x) for x in batch.column(1).to_pylist()]
            as_rows = lambda spans: [{"kind": k, "start": a, "end": b} for a, k, b in spans]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0), pa.array([as_rows(b) for b, _, _ in found], pa.list_(_SPAN)),
                    pa.array([as_rows(a) for _, a, _ in found], pa.list_(_SPAN)), pa.array([n for _, _, n in found], pa.int64()),
                ],
                ["doc_id", "base_spans", "spans", "layers"],
            )

    return map_batches(texts(docs, id_col, text_col), work, f"doc_id long, base_spans {_SPAN_SQL}, spans {_SPAN_SQL}, layers long")


def redact_documents(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The same rows and columns with all secrets in `text_col` replaced; null texts stay null."""
    names = docs.columns
    at = names.index(text_col)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bodies = [x if x is None else redact(x, scan(x)[1]) for x in batch.column(at).to_pylist()]
            columns = [pa.array(bodies, batch.schema.field(at).type) if i == at else c for i, c in enumerate(batch.columns)]
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    return map_batches(docs, work, row_schema(docs))


def joined(spans):
    """kind:start:end, comma-joined (column)."""
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))
