"""FLAC media columns: encoder and decoder in numpy, many frames in step.

Bytes are stored as mono 8-bit samples (a byte less 128). The stream is standard FLAC: STREAMINFO
with the MD5 of the samples, a SEEKTABLE with one point per frame, and frames of `BLOCK` samples
(the last may be shorter). A frame's subframe is constant, verbatim, a fixed predictor of order 0
to 4, or a linear predictor with quantised coefficients; residuals are Rice-coded in one
partition. Decoding accepts these, and residuals in several partitions, both parameter widths,
and escaped partitions.

The work on samples is vectorised across frames: `GROUP_FRAMES` frames, of one stream or of many, are encoded
and decoded side by side, one sample position (or one checksum byte) per numpy step, so that working memory
does not grow with a text. Frame headers carry CRC-8 and frames CRC-16; both are verified before samples are given out.

Defined results: null and empty texts are a payload of 64 zero bytes; repeated rows each give a row;
a null doc_id stays null; an empty table gives no rows; other columns are ignored. Damaged streams
raise `FlacError`.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_batches, texts

BLOCK = 256
UNIT = 64
RATE = 8000
LPC_ORDER = 4
LPC_BITS = 10
#: Frames that are worked on side by side, and bytes of payload that are held at a time (one text at least).
GROUP_FRAMES = 8192
GROUP_BYTES = 2_000_000


class FlacError(ValueError):
    """The stream is not FLAC, or a checksum does not hold."""


def _crc_table(width: int, poly: int) -> np.ndarray:
    out = np.zeros(256, np.uint32)
    for b in range(256):
        c = b << (width - 8)
        for _ in range(8):
            c = (c << 1) ^ poly if c >> (width - 1) else c << 1
            c &= (1 << width) - 1
        out[b] = c
    return out


# Fixed values of the format: checksum polynomials x^8+x^2+x+1 and x^16+x^15+x^2+1; predictor weights.
_CRC8, _CRC16 = _crc_table(8, 0x07), _crc_table(16, 0x8005)
_FIXED = {0: (), 1: (1,), 2: (2, -1), 3: (3, -3, 1), 4: (4, -6, 4, -1)}


def crc(table: np.ndarray, width: int, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Checksums of many stretches of one byte array, one byte of each per step."""
    out = np.zeros(len(starts), np.uint32)
    if not len(starts):
        return out
    order = np.argsort(starts - ends, kind="stable")  # longest first
    at, left = starts[order].copy(), (ends - starts)[order]
    mask, value = np.uint32((1 << width) - 1), np.zeros(len(order), np.uint32)
    counts = np.searchsorted(-left, -np.arange(1, int(left[0]) + 1), side="right") if left[0] > 0 else []
    for n in counts:
        v = value[:n]
        value[:n] = ((v << np.uint32(8)) ^ table[(v >> np.uint32(width - 8)) ^ data[at[:n]]]) & mask
        at[:n] += 1
    out[order] = value
    return out


def utf8_number(n: int) -> bytes:
    """The format's extended UTF-8 coding of a frame number."""
    if n < 0x80:
        return bytes([n])
    tail: list[int] = []
    lead = 0x3F
    while n > lead:
        tail.append(0x80 | n & 0x3F)
        n >>= 6
        lead >>= 1
    return bytes([(~lead << 1) & 0xFF | n, *reversed(tail)])


# ------------------------------------------------------------------ encoding


def _predict(x: np.ndarray, weights: np.ndarray, shift: np.ndarray) -> np.ndarray:
    """Residuals of rows of samples (frames by positions); weights by frame, most recent first."""
    order = weights.shape[1]
    if not order:
        return x
    total = np.zeros((x.shape[0], x.shape[1] - order), np.int32)
    for j in range(order):
        total += weights[:, j : j + 1] * x[:, order - 1 - j : x.shape[1] - 1 - j]
    return x[:, order:] - (total >> shift[:, None])


def _lpc(x: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """Quantised prediction weights and their shift for each row (Levinson-Durbin on the rows' autocorrelation)."""
    n = x.shape[1]
    windowed = x * np.sin(np.pi * (np.arange(n) + 0.5) / n)
    r = np.stack([(windowed[:, : n - k] * windowed[:, k:]).sum(axis=1) for k in range(order + 1)], axis=1)
    r[:, 0] = r[:, 0] * 1.0001 + 1e-6
    a, error = np.zeros((len(x), order)), r[:, 0].copy()
    for i in range(order):
        k = (r[:, i + 1] - (a[:, :i] * r[:, i:0:-1]).sum(axis=1)) / error
        a[:, :i] -= k[:, None] * a[:, :i][:, ::-1]
        a[:, i] = k
        error *= np.maximum(1 - k * k, 1e-9)
    top = np.abs(a).max(axis=1)
    shift = np.clip(LPC_BITS - 2 - np.ceil(np.log2(np.maximum(top, 1e-9))), 0, 15).astype(np.int32)
    limit = (1 << (LPC_BITS - 1)) - 1
    return np.clip(np.rint(a * (1 << shift)[:, None]), -limit - 1, limit).astype(np.int32), shift


def _folded(residual: np.ndarray) -> np.ndarray:
    """Signed to unsigned, small magnitudes first."""
    return (residual << 1) ^ (residual >> 31)


def _rice(folded: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Per frame: bits of the best Rice parameter near the mean's logarithm, and that parameter."""
    n = folded.shape[1]
    guess = np.clip(np.log2(np.maximum(folded.mean(axis=1), 1.0)).astype(np.int32), 0, 11)
    best, bits = guess, np.full(len(folded), 1 << 40)
    for k in (guess, np.maximum(guess - 1, 0)):
        cost = (folded >> k[:, None]).sum(axis=1) + n * (k.astype(np.int64) + 1)
        best, bits = np.where(cost < bits, k, best), np.minimum(cost, bits)
    return bits, best


class _BitRows:
    """Bits of many frames, gathered as (frame, value, width) columns and laid out at once."""

    def __init__(self, frames: int):
        self.n, self.fields = frames, []

    def put(self, value, width) -> None:
        value = np.asarray(value, np.int32)
        value = value if value.ndim == 2 else np.broadcast_to(value, (self.n,))[:, None]
        width = np.asarray(width, np.int32)
        width = np.broadcast_to(width if width.ndim == 2 else width.reshape(-1, 1), value.shape)
        self.fields.append((value, width))

    def bytes(self) -> tuple[np.ndarray, np.ndarray]:
        """All frames' bytes, each padded to whole bytes, and the frames' byte lengths."""
        value = np.concatenate([v for v, _ in self.fields], axis=1)
        ends = np.cumsum(np.concatenate([w for _, w in self.fields], axis=1), axis=1, dtype=np.int64)
        length = (ends[:, -1] + 7) // 8
        begin = np.concatenate([[0], np.cumsum(length * 8)[:-1]])
        last = (ends + (begin[:, None] - 1)).ravel()  # each field's last bit; what precedes its ones are zeros
        value = value.ravel()
        bits = np.zeros(int(length.sum()) * 8, np.uint8)
        for b in range(int(value.max(initial=0)).bit_length()):
            bits[last[(value >> b) & 1 == 1] - b] = 1
        return np.packbits(bits), length


def _encode_frames(x: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Frames of equally many samples (rows of x): their bytes joined, and their lengths."""
    frames, n = x.shape
    zero = np.zeros(frames, np.int32)
    plans: list[tuple[str, int, np.ndarray, np.ndarray, np.ndarray]] = []
    for order in range(min(5, n)):
        weights = np.tile(np.array(_FIXED[order], np.int32), (frames, 1))
        plans.append(("fixed", order, weights, zero, _predict(x, weights, zero)))
    if n >= 32:
        weights, shift = _lpc(x.astype(np.float64), LPC_ORDER)
        plans.append(("lpc", LPC_ORDER, weights, shift, _predict(x, weights, shift)))
    size = np.stack([np.abs(r).sum(axis=1) + o * 64 for _, o, _, _, r in plans])
    choice = size.argmin(axis=0)
    choice[(x == x[:, :1]).all(axis=1)] = -2
    parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    rice: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    for c in range(len(plans)):  # a Rice coding that is no smaller than the plain samples gives way to them
        rows = np.flatnonzero(choice == c)
        kind, order, _, _, residual = plans[c]
        folded = _folded(residual[rows])
        bits, k = _rice(folded)
        plain = bits + 10 + 8 * order + (9 + LPC_BITS * order if kind == "lpc" else 0) >= 8 * n
        choice[rows[plain]] = -1
        rice[c] = folded[~plain], k[~plain]
    for c in np.unique(choice):
        rows = np.flatnonzero(choice == c)
        out = _BitRows(len(rows))
        xs = x[rows]
        if c == -2:
            out.put(0, 8)
            out.put(xs[:, 0] & 0xFF, 8)
        elif c == -1:
            out.put(0b00000010, 8)
            out.put(xs & 0xFF, 8)
        else:
            kind, order, weights, shift, _ = plans[c]
            folded, k = rice[c]
            out.put((8 | order if kind == "fixed" else 32 | order - 1) << 1, 8)
            out.put(xs[:, :order] & 0xFF, 8)
            if kind == "lpc":
                out.put(LPC_BITS - 1, 4)
                out.put(shift[rows], 5)
                out.put(weights[rows] & ((1 << LPC_BITS) - 1), LPC_BITS)
            out.put(0, 6)  # four-bit parameters, one partition
            out.put(k, 4)
            k = k[:, None]
            out.put((1 << k) | (folded & ((1 << k) - 1)), (folded >> k) + 1 + k)
        data, length = out.bytes()
        parts.append((rows, data, length))
    heads = [_frame_head(int(i), n) for i in number]
    body_length = np.zeros(frames, np.int64)
    for rows, _, length in parts:
        body_length[rows] = length
    head_length = np.fromiter(map(len, heads), np.int64, frames)
    total = head_length + body_length + 2
    begin = np.concatenate([[0], np.cumsum(total)[:-1]])
    whole = np.zeros(int(total.sum()), np.uint8)
    _place(whole, begin, np.frombuffer(b"".join(heads), np.uint8), head_length)
    for rows, data, length in parts:
        _place(whole, begin[rows] + head_length[rows], data, length)
    check = crc(_CRC16, 16, whole, begin, begin + total - 2)
    whole[begin + total - 2], whole[begin + total - 1] = check >> 8, check & 0xFF
    return whole, total


def _place(whole: np.ndarray, begin: np.ndarray, data: np.ndarray, length: np.ndarray) -> None:
    """Copies stretches of `data`, one after the other there, to their places."""
    offset = np.concatenate([[0], np.cumsum(length)[:-1]])
    whole[np.repeat(begin - offset, length) + np.arange(len(data))] = data


_HEADS: dict[tuple[int, int], bytes] = {}


def _frame_head(number: int, n: int) -> bytes:
    if (number, n) not in _HEADS:
        size = {256: 8, 512: 9, 1024: 10, 2048: 11, 4096: 12}.get(n, 7)
        head = bytes([0xFF, 0xF8, size << 4, 0x02]) + utf8_number(number) + (struct.pack(">H", n - 1) if size == 7 else b"")
        value = 0
        for b in head:
            value = int(_CRC8[value ^ b])
        if len(_HEADS) > 100_000:
            _HEADS.clear()
        _HEADS[number, n] = head + bytes([value])
    return _HEADS[number, n]


def encode(payloads: list[bytes], block: int = BLOCK) -> list[bytes]:
    """FLAC streams of 8-bit payloads, encoded side by side. Payloads must not be empty."""
    sizes = np.array([len(p) for p in payloads], np.int64)
    counts = -(-sizes // block)
    base, first = (np.concatenate([[0], np.cumsum(x)]) for x in (sizes, counts))
    joined = np.frombuffer(payloads[0] if len(payloads) == 1 else b"".join(payloads), np.uint8)
    coded: list[bytes] = [b""] * int(first[-1])
    for low in range(0, len(coded), GROUP_FRAMES):
        frame = np.arange(low, min(low + GROUP_FRAMES, len(coded)))
        owner = np.searchsorted(first, frame, side="right") - 1
        number = frame - first[owner]
        start = base[owner] + number * block
        length = np.minimum(block, base[owner + 1] - start)
        for n in np.unique(length):
            rows = np.flatnonzero(length == n)
            samples = joined[start[rows][:, None] + np.arange(n)].astype(np.int32) - 128
            data, each = _encode_frames(samples, number[rows])
            raw, cut = data.tobytes(), np.concatenate([[0], np.cumsum(each)])
            for r, a, b in zip(frame[rows].tolist(), cut[:-1].tolist(), cut[1:].tolist()):
                coded[r] = raw[a:b]
    streams = []
    for p, a, b in zip(payloads, first[:-1].tolist(), first[1:].tolist()):
        streams.append(b"".join([_stream_head(p, coded[a:b], block), *coded[a:b]]))
        coded[a:b] = [b""] * (b - a)
    return streams


def _stream_head(payload: bytes, frames: list[bytes], block: int) -> bytes:
    lengths = [len(f) for f in frames]
    signed = payload.translate(_FLIP)
    info = struct.pack(">HH", max(16, block), max(16, block)) + min(lengths).to_bytes(3, "big") + max(lengths).to_bytes(3, "big")
    info += (RATE << 44 | 0 << 41 | 7 << 36 | len(payload)).to_bytes(8, "big") + hashlib.md5(signed).digest()
    points, offset = [], 0
    for k, n in enumerate(lengths):
        points.append(struct.pack(">QQH", k * block, offset, min(block, len(payload) - k * block)))
        offset += n
    table = b"".join(points)
    # a table longer than a metadata block can be goes on in further SEEKTABLE-sized application-free blocks: thin it out
    step = -(-len(table) // (18 * 900_000))
    table = b"".join(points[::step]) if step > 1 else table
    return b"fLaC" + b"\x00" + len(info).to_bytes(3, "big") + info + b"\x83" + len(table).to_bytes(3, "big") + table


_FLIP = bytes(b ^ 0x80 for b in range(256))


# ------------------------------------------------------------------ decoding


def read_metadata(stream: bytes) -> tuple[dict, int]:
    """STREAMINFO and SEEKTABLE fields, and where the frames begin."""
    if stream[:4] != b"fLaC":
        raise FlacError("no FLAC marker")
    at, last, found = 4, False, {"points": np.zeros((0, 3), np.int64)}
    while not last:
        if at + 4 > len(stream):
            raise FlacError("metadata is cut off")
        last, kind, n = stream[at] >> 7, stream[at] & 0x7F, int.from_bytes(stream[at + 1 : at + 4], "big")
        body = stream[at + 4 : at + 4 + n]
        at += 4 + n
        if kind == 0:
            word = int.from_bytes(body[10:18], "big")
            found |= {"block": struct.unpack(">H", body[2:4])[0], "rate": word >> 44, "channels": (word >> 41 & 7) + 1, "bits": (word >> 36 & 31) + 1, "samples": word & (1 << 36) - 1, "md5": body[18:34]}
        elif kind == 3:
            points = np.frombuffer(body, np.dtype([("sample", ">u8"), ("offset", ">u8"), ("n", ">u2")]))
            found["points"] = np.stack([points[c].astype(np.int64) for c in ("sample", "offset", "n")], axis=1).reshape(-1, 3)
    if "bits" not in found:
        raise FlacError("no STREAMINFO")
    return found, at


class _Reader:
    """Bit positions of many frames in one byte array; reads a field of every active frame per call."""

    def __init__(self, data: np.ndarray, at: np.ndarray):
        padded = np.concatenate([data, np.zeros(16, np.uint8)])
        self.data = padded
        # 32-bit windows at every byte, so that a field of up to 24 bits is one gather
        self.window = (padded[:-3].astype(np.uint32) << 24) | (padded[1:-2].astype(np.uint32) << 16) | (padded[2:-1].astype(np.uint32) << 8) | padded[3:]
        ones = np.unpackbits(data)
        # next set bit at or after each bit, for unary runs
        place = np.where(ones == 1, np.arange(len(ones), dtype=np.int64), np.int64(len(ones)))
        self.next_one = np.concatenate([np.minimum.accumulate(place[::-1])[::-1], np.full(64, len(ones))])
        self.at = at.astype(np.int64) * 8

    def take(self, rows: np.ndarray, width) -> np.ndarray:
        """Unsigned fields of up to 24 bits."""
        at = self.at[rows]
        width = np.broadcast_to(np.asarray(width, np.int64), at.shape)
        self._check(at + width)
        value = (self.window[at >> 3].astype(np.uint64) << (at & 7).astype(np.uint64)) & np.uint64(0xFFFFFFFF)
        self.at[rows] = at + width
        return np.where(width > 0, value >> (32 - width).astype(np.uint64), 0).astype(np.int64)

    def signed(self, rows: np.ndarray, width) -> np.ndarray:
        value = self.take(rows, width)
        return value - ((value >> (np.asarray(width) - 1)) << np.asarray(width))

    def unary(self, rows: np.ndarray) -> np.ndarray:
        at = self.at[rows]
        self._check(at)
        one = self.next_one[at]
        self._check(one + 1)
        self.at[rows] = one + 1
        return one - at

    def _check(self, at: np.ndarray) -> None:
        if at.size and at.max() > 8 * (len(self.data) - 16):
            raise FlacError("a frame is cut off")


def _frame_starts(stream: bytes, meta: dict, at: int) -> np.ndarray:
    points = meta["points"]
    expected = -(-meta["samples"] // max(1, meta["block"]))
    if len(points) == expected:
        return at + points[:, 1]
    raise FlacError("the stream has no seek point for every frame")


def decode(streams: list[bytes], verify: bool = True) -> list[np.ndarray]:
    """Samples (16-bit integers) of mono streams, decoded side by side; checksums and MD5 verified."""
    metas, starts, ends = [], [], []
    base = np.concatenate([[0], np.cumsum([len(s) for s in streams])])
    for i, s in enumerate(streams):
        meta, at = read_metadata(s)
        if meta["channels"] != 1 or meta["bits"] != 8:
            raise FlacError("only mono streams of 8-bit samples are decoded")
        metas.append(meta)
        found = base[i] + _frame_starts(s, meta, at)
        starts.append(found)
        ends.append(np.append(found[1:], base[i + 1]))
    data = np.frombuffer(streams[0] if len(streams) == 1 else b"".join(streams), np.uint8)
    begin, end = (np.concatenate(x).astype(np.int64) for x in (starts, ends))
    parts, sizes = [np.empty(0, np.int16)], [np.empty(0, np.int64)]
    for low in range(0, len(begin), GROUP_FRAMES):
        a, b = begin[low : low + GROUP_FRAMES], end[low : low + GROUP_FRAMES]
        samples, n, _ = decode_frames(data[a[0] : b[-1]], a - a[0], b - a[0], verify)
        parts.append(samples.astype(np.int16))
        sizes.append(n)
    samples, out = np.concatenate(parts), []
    cut = np.concatenate([[0], np.cumsum([len(x) for x in starts])])
    at = np.concatenate([[0], np.cumsum(np.concatenate(sizes))])[cut]
    for meta, a, b in zip(metas, at[:-1], at[1:]):
        found = samples[a:b]
        if len(found) != meta["samples"]:
            raise FlacError("the number of samples differs from STREAMINFO")
        if verify and any(meta["md5"]) and hashlib.md5(found.astype(np.int8)).digest() != meta["md5"]:
            raise FlacError("the MD5 of the samples differs from STREAMINFO")
        out.append(found)
    return out


def decode_frames(data: np.ndarray, begin: np.ndarray, end: np.ndarray, verify: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Samples of frames one after the other, samples per frame, and each frame's number."""
    frames = len(begin)
    everyone = np.arange(frames)
    if (end - begin < 8).any():
        raise FlacError("a frame is cut off")
    read = _Reader(data, begin)
    if (read.take(everyone, 16) != 0xFFF8).any():
        raise FlacError("a frame does not begin with the sync code of fixed block sizes")
    size_code, rate_code = read.take(everyone, 4), read.take(everyone, 4)
    layout = read.take(everyone, 8)
    if (rate_code != 0).any() or (layout != 0x02).any():
        raise FlacError("only mono frames of 8-bit samples are decoded")
    lead = read.take(everyone, 8)
    more = np.select([lead < 0x80, lead < 0xE0, lead < 0xF0, lead < 0xF8, lead < 0xFC, lead < 0xFE], [0, 1, 2, 3, 4, 5], 6)
    number = np.where(more == 0, lead, lead & ((1 << np.maximum(0, 6 - more)) - 1))
    for k in range(6):
        rows = everyone[more > k]
        if rows.size:
            number[rows] = number[rows] << 6 | read.take(rows, 8) & 0x3F
    n = np.where(size_code >= 8, 256 << np.maximum(0, size_code - 8), np.where(size_code >= 2, 576 << np.clip(size_code - 2, 0, 3), 192))
    for code, width in ((6, 8), (7, 16)):
        rows = everyone[size_code == code]
        if rows.size:
            n[rows] = read.take(rows, width) + 1
    head_end = read.at >> 3
    check8 = read.take(everyone, 8)
    if verify and (crc(_CRC8, 8, data, begin, head_end) != check8).any():
        raise FlacError("a frame header's CRC-8 does not hold")
    if verify and (crc(_CRC16, 16, data, begin, end - 2) != (data[end - 2].astype(np.uint32) << 8 | data[end - 1])).any():
        raise FlacError("a frame's CRC-16 does not hold")
    kind = read.take(everyone, 8)
    if (kind & 0x81).any():
        raise FlacError("reserved bit set, or wasted bits, which 8-bit payloads don't use")
    kind >>= 1
    width = int(n.max(initial=0))
    x = np.zeros((width, frames), np.int64)  # position by frame
    constant, verbatim = everyone[kind == 0], everyone[kind == 1]
    if constant.size:
        x[:, constant] = read.signed(constant, 8)
    for i in range(int(n[verbatim].max(initial=0))):
        rows = verbatim[n[verbatim] > i]
        x[i, rows] = read.signed(rows, 8)
    fixed, lpc = (kind >= 8) & (kind <= 12), kind >= 32
    if not (fixed | lpc | (kind <= 1)).all():
        raise FlacError("reserved subframe type")
    order = np.where(fixed, kind - 8, np.where(lpc, kind - 31, 0))
    coded = everyone[fixed | lpc]
    top = int(order.max(initial=0))
    for i in range(top):
        rows = coded[order[coded] > i]
        x[i, rows] = read.signed(rows, 8)
    weights, shift = np.zeros((max(4, top), frames), np.int64), np.zeros(frames, np.int64)
    for o, w in _FIXED.items():
        rows = everyone[fixed & (order == o)]
        for j, v in enumerate(w):
            weights[j, rows] = v
    rows = everyone[lpc]
    if rows.size:
        precision = read.take(rows, 4) + 1
        shift[rows] = read.signed(rows, 5)
        if (precision == 16).any() or (shift[rows] < 0).any():
            raise FlacError("reserved coefficient precision or shift")
        for j in range(int(order[rows].max())):
            some = order[rows] > j
            weights[j, rows[some]] = read.signed(rows[some], precision[some])
    _residuals(read, coded, order, n, x)
    for o in np.unique(order[coded]):  # restore, one sample position of all frames per step
        rows = coded[order[coded] == o]
        if o == 0:
            continue
        w, s, part = weights[:o, rows], shift[rows], np.ascontiguousarray(x[:, rows])
        for i in range(o, int(n[rows].max())):
            total = np.zeros(len(rows), np.int64)
            for j in range(o):
                total += w[j] * part[i - 1 - j]
            part[i] += total >> s
        x[:, rows] = part
    return x.T[np.arange(width)[None, :] < n[:, None]], n, number


def _residuals(read: _Reader, rows: np.ndarray, order: np.ndarray, n: np.ndarray, x: np.ndarray) -> None:
    """Rice-coded residuals of the frames, written behind their warm-up samples."""
    if not rows.size:
        return
    method = read.take(rows, 2)
    if (method > 1).any():
        raise FlacError("reserved residual coding")
    parts = np.int64(1) << read.take(rows, 4)
    each = n[rows] // parts
    wide = np.where(method == 1, 5, 4)
    k, escaped = np.zeros(len(rows), np.int64), np.zeros(len(rows), bool)
    first = order[rows]
    stop = n[rows]
    for i in range(int(first.min()), int(stop.max())):
        live = (i >= first) & (i < stop)
        new = live & ((i == first) | (i % np.maximum(1, each) == 0))
        at = np.flatnonzero(new)
        if at.size:  # a partition begins: its parameter, or an escape with the width of plain values
            k[at] = read.take(rows[at], wide[at])
            escaped[at] = k[at] == (1 << wide[at]) - 1
            e = at[escaped[at]]
            if e.size:
                k[e] = read.take(rows[e], 5)
        at = np.flatnonzero(live & ~escaped)
        if at.size:
            r = rows[at]
            high = read.unary(r)
            folded = high << k[at] | read.take(r, k[at])
            x[i, r] = (folded >> 1) ^ -(folded & 1)
        at = np.flatnonzero(live & escaped)
        if at.size:
            some = at[k[at] > 0]
            x[i, rows[at]] = 0
            if some.size:
                x[i, rows[some]] = read.signed(rows[some], k[some])


def seek(stream: bytes, first: int, count: int) -> bytes:
    """`count` payload bytes from sample `first`, decoding only the frames that hold them."""
    meta, at = read_metadata(stream)
    points = meta["points"]
    starts = at + points[:, 1]
    ends = np.append(starts[1:], len(stream))
    a = int(np.searchsorted(points[:, 0], first, side="right")) - 1
    b = int(np.searchsorted(points[:, 0], first + count, side="left"))
    samples, _, _ = decode_frames(np.frombuffer(stream, np.uint8), starts[a:b].astype(np.int64), ends[a:b].astype(np.int64))
    off = first - int(points[a, 0])
    return (samples[off : off + count] + 128).astype(np.uint8).tobytes()


# ------------------------------------------------------------------ operators


def payload(text: str) -> tuple[int, bytes]:
    """Length of the text's UTF-8, and that with zeros up to a positive multiple of 64."""
    raw = text.encode("utf-8", "replace")
    return len(raw), raw.ljust(max(UNIT, -(-len(raw) // UNIT) * UNIT), b"\0")


def _groups(sizes: list[int], most: int = GROUP_BYTES) -> Iterator[slice]:
    start = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield slice(start, i)
            start, total = i, 0
        total += n
    if len(sizes) > start:
        yield slice(start, len(sizes))


def encode_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, media (binary FLAC stream) for every row."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            whole = [payload(x) for x in batch.column(1).to_pylist()]
            for part in _groups([len(p) for _, p in whole]):
                streams = encode([p for _, p in whole[part]])
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0)[part.start : part.stop], pa.array([n for n, _ in whole[part]], pa.int64()), pa.array(streams, pa.binary())],
                    ["doc_id", "n_bytes", "media"],
                )

    return map_batches(texts(docs, id_col, text_col), work, "doc_id long, n_bytes long, media binary")


def features_of(samples: np.ndarray, most: int = 1 << 20) -> str:
    """Peak, energy, zero crossings and sum of steps of the samples, as text."""
    peak = energy = crossings = steps = 0
    for at in range(0, len(samples), most):
        x = samples[max(0, at - 1) : at + most].astype(np.int64)  # with the sample before, for what lies between two
        own = x[1:] if at else x
        peak, energy = max(peak, int(np.abs(own).max(initial=0))), energy + int((own * own).sum())
        crossings, steps = crossings + int(((x[1:] ^ x[:-1]) < 0).sum()), steps + int(np.abs(np.diff(x)).sum())
    return f"peak={peak};energy={energy};crossings={crossings};steps={steps}"


def read_media(media: DataFrame) -> DataFrame:
    """Decoded digests of doc_id, n_bytes, media: what was stored, read back and verified."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, n_bytes, streams = (batch.column(k).to_pylist() for k in range(3))
            for part in _groups([len(s) for s in streams]):
                rows = []
                for doc, n, stream, samples in zip(ids[part], n_bytes[part], streams[part], decode(streams[part])):
                    back = (samples + 128).astype(np.uint8).tobytes()
                    rows.append((doc, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(stream), hashlib.sha256(stream).hexdigest(), features_of(samples)))
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows), kinds)], _DIGESTS)

    return map_batches(media.select("doc_id", "n_bytes", "media"), work, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


_DIGESTS = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]


def pcm_blocks(media: DataFrame) -> DataFrame:
    """PCM blocks with sample offsets: doc_id, block, first_sample, n_samples, pcm (signed 8-bit)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc, stream in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                samples = decode([stream])[0].astype(np.int8).tobytes()
                at = read_metadata(stream)[0]["points"]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([doc] * len(at), pa.int64()), pa.array(range(len(at)), pa.int32()), pa.array(at[:, 0], pa.int64()),
                        pa.array(at[:, 2], pa.int64()), pa.array([samples[a : a + n] for a, _, n in at.tolist()], pa.binary()),
                    ],
                    ["doc_id", "block", "first_sample", "n_samples", "pcm"],
                )

    return map_batches(media.select("doc_id", "media"), work, "doc_id long, block int, first_sample long, n_samples long, pcm binary")
