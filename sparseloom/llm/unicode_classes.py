"""Character classes of the plain Latin range, for fast exact pre-tokenisation.

Within this range (white space, printable ASCII, Latin-1 letters and signs, Latin
Extended-A and -B) NFC changes nothing and every Unicode version agrees on the
categories, so Python's `re` gives the same pieces as the tokenizer libraries. Texts with
any other character take the general path of the operator instead.
"""

from __future__ import annotations

import re
import unicodedata

_LAST = 0x24F
_PLAIN = [*map(ord, "\t\n\r"), *range(0x20, 0x7F), *range(0xA1, 0xAD), *range(0xAE, _LAST + 1)]


def _ranges(codes: list[int]) -> str:
    out, start = [], None
    for i, c in enumerate(codes):
        start = c if start is None else start
        if i + 1 == len(codes) or codes[i + 1] != c + 1:
            out.append(f"\\u{start:04x}-\\u{c:04x}" if c > start else f"\\u{c:04x}")
            start = None
    return "".join(out)


def _of(kind: str) -> str:
    return _ranges([c for c in _PLAIN if unicodedata.category(chr(c)).startswith(kind)])


LETTERS, NUMBERS = _of("L"), _of("N")
#: Finds a character for which the plain classes are not known to be exact.
UNUSUAL = re.compile(f"[^{_ranges(sorted(_PLAIN))}]")


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    shown = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    hidden = iter(range(0x100, 0x200))
    return [chr(b) if b in shown else chr(next(hidden)) for b in range(256)]
