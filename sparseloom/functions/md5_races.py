"""The md5 draws of whole arrays at once, in numpy: what `rng.h52` gives for each, without a call for each."""

from __future__ import annotations

import numpy as np

_TURNS = np.array([7, 12, 17, 22, 5, 9, 14, 20, 4, 11, 16, 23, 6, 10, 15, 21]).reshape(4, 4)
_SINES = (np.abs(np.sin(np.arange(1, 65))) * 2**32).astype(np.uint64).astype(np.uint32)
_START = np.array([0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476], np.uint32)
_AT = [np.arange(16), (5 * np.arange(16) + 1) % 16, (3 * np.arange(16) + 5) % 16, 7 * np.arange(16) % 16]
#: Bytes of a message that fits one block, besides its end mark and its length.
LONGEST = 55
#: Messages worked on at once: their words stay in the cache.
TOGETHER = 1 << 14
#: Above every draw.
TAKEN = np.int64(np.iinfo(np.int64).max)


def _compress(words: list[np.ndarray | np.uint32], n: int) -> np.ndarray:
    """The first 52 bits of the digests of n messages of one block each, given as 16 little-endian words (arrays, or one for all)."""
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        turn = i // 16
        if turn == 0:
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif turn == 1:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif turn == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        f += a
        w = words[_AT[turn][i % 16]]
        if isinstance(w, np.ndarray):
            f += w
            f += _SINES[i]
        else:
            f += np.uint32((int(w) + int(_SINES[i])) & 0xFFFFFFFF)
        r = int(_TURNS[turn, i % 4])
        np.left_shift(f, np.uint32(r), out=t)
        np.right_shift(f, np.uint32(32 - r), out=f)
        np.bitwise_or(f, t, out=f)
        f += b
        a, d, c, b, f = d, c, b, f, a  # the old a is free to be written
    a += _START[0]
    b += _START[1]
    high, low = a.byteswap().astype(np.uint64), b.byteswap().astype(np.uint64)
    return ((high << np.uint64(20)) | (low >> np.uint64(12))).astype(np.int64)


#: Four decimal digits, leading zeros kept, as a little-endian word.
_FOUR = np.frombuffer("".join(f"{k:04d}" for k in range(10_000)).encode(), "<u4").astype(np.uint64)
_TENS = np.array([10**k for k in range(1, 8)])


def _digits(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Decimal digits of numbers from 0 to below 10^8: a little-endian word of 8 bytes, the rest zero, and how many digits."""
    many = np.searchsorted(_TENS, ids, side="right") + 1
    high = ids // 10_000
    word = _FOUR[high] | (_FOUR[ids - high * 10_000] << np.uint64(32))
    return word >> ((8 - many) * 8).astype(np.uint64), many


def draws(stems: list[bytes], lengths: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Draws of `stem` followed by an id in decimal: `lengths[k]` consecutive ids belong to `stems[k]`."""
    out = np.empty(len(ids), np.int64)
    size = np.array([len(s) for s in stems], np.int64)
    owner = np.repeat(np.arange(len(stems)), lengths)
    plain = (ids >= 0) & (ids < 10**8)
    fits = plain & (size[owner] <= LONGEST - 8)
    if not fits.all():
        import hashlib

        for k in np.flatnonzero(~fits):
            out[k] = int(hashlib.md5(stems[owner[k]] + str(ids[k]).encode()).hexdigest()[:13], 16)
        at = np.flatnonzero(fits)
        if len(at):
            out[at] = _of_one_block(stems, size, owner[at], ids[at])
        return out
    return _of_one_block(stems, size, owner, ids)


def _of_one_block(stems: list[bytes], size: np.ndarray, owner: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """All messages of stems of at most 47 bytes and ids of at most 8 digits."""
    out = np.empty(len(ids), np.int64)
    held = np.zeros((len(stems), 64), np.uint8)
    for k, s in enumerate(stems):
        if len(s) <= LONGEST - 8:
            held[k, : len(s)] = np.frombuffer(s, np.uint8)
    blocks = held.view(np.uint32)
    for n in np.unique(size[owner]):
        of = np.flatnonzero(size[owner] == n) if (size[owner] != n).any() else None
        whose, of_ids = (owner, ids) if of is None else (owner[of], ids[of])
        got = np.empty(len(of_ids), np.int64)
        first, shift = int(n) // 4, np.uint64(int(n) % 4 * 8)
        # words before the first that the digits touch are the stem's own; where all stems agree they are one for all
        same = [len(np.unique(blocks[size == n, w])) == 1 for w in range(16)]
        some = blocks[np.flatnonzero(size == n)[0]]
        for low in range(0, len(of_ids), TOGETHER):
            own, now = whose[low : low + TOGETHER], of_ids[low : low + TOGETHER]
            word, many = _digits(now)
            mark = many.astype(np.uint64) << np.uint64(3)
            end = np.where(many < 8, np.uint64(0x80) << np.minimum(mark, np.uint64(56)), np.uint64(0))
            word = word | end
            words: list = [some[w] if same[w] else blocks[own, w] for w in range(first)] + [np.uint32(0)] * (16 - first)
            placed = word << shift
            words[first] = (placed & np.uint64(0xFFFFFFFF)).astype(np.uint32) | blocks[own, first]
            words[first + 1] = (placed >> np.uint64(32)).astype(np.uint32)
            over = (word >> (np.uint64(64) - shift)) if shift else np.zeros(len(now), np.uint64)
            # an id of eight digits has its end mark in the byte after them
            over = over | np.where(many == 8, np.uint64(0x80) << shift, np.uint64(0))
            words[first + 2] = over.astype(np.uint32)
            words[14] = ((many + n) * 8).astype(np.uint32)
            got[low : low + TOGETHER] = _compress(words, len(now))
        if of is None:
            return got
        out[of] = got
    return out


def smallest(keys: np.ndarray, lengths: np.ndarray, s: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of the `s` smallest keys of each row in order, equal ones as they lie; and how many each row has."""
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]]).astype(np.int64)
    counts = np.minimum(lengths, s)
    if s > 16:
        owner = np.repeat(np.arange(len(lengths)), lengths)
        order = np.lexsort((keys, owner))
        inside = np.arange(len(keys)) - np.repeat(starts, lengths)
        return order[inside < s], counts
    left, picked = keys.copy(), np.full((len(lengths), s), -1, np.int64)
    full = np.flatnonzero(lengths > 0)
    for turn in range(min(s, int(lengths.max(initial=0)))):
        least = np.minimum.reduceat(left, starts[full])
        hit = np.flatnonzero(left == np.repeat(least, lengths[full]))
        row = np.searchsorted(starts[full], hit, side="right") - 1
        first = np.concatenate([[True], row[1:] != row[:-1]])
        hit, row = hit[first], full[row[first]]
        live = turn < counts[row]
        picked[row[live], turn] = hit[live]
        left[hit] = TAKEN
    return picked[picked >= 0], counts
