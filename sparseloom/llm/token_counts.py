"""Token counts without token ids: byte-pair merging with a heap over a linked list.

A text is split into pieces by the vocabulary's pre-tokenisation pattern. Every piece
starts as one symbol per UTF-8 byte, chained by next/previous links. A heap holds the
ranks of adjacent pairs that may merge; the lowest rank (leftmost first) is popped, checked
against the links as they are now, merged in place, and the two new neighbour pairs are
pushed. Each merge takes one symbol away, so the piece has `bytes - merges` tokens. Pieces
recur, so each worker remembers the count of a bounded number of them.

Defined results: null and empty texts have 0 bytes and 0 tokens and are not over the limit;
repeated rows each give a row; a null doc_id stays null; other columns are ignored.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Remembered, map_batches, texts, tokenizer_path
from .unicode_classes import LETTERS, NUMBERS, UNUSUAL, byte_symbols

#: Pieces that a worker remembers; beyond it, the memory is emptied and filled anew.
REMEMBERED_PIECES = 400_000

_CONTRACTIONS = "'s|'t|'re|'ve|'m|'ll|'d"
#: The vocabulary's own splitting rule, for the plain Latin range.
_PLAIN_PIECES = re.compile(
    f"{_CONTRACTIONS}| ?[{LETTERS}]+| ?[{NUMBERS}]+| ?[^\\s{LETTERS}{NUMBERS}]+|\\s+(?!\\S)|\\s+"
)
#: No piece crosses from text into white space, so chunks of whole pieces can be remembered.
_PLAIN_CHUNKS = re.compile("(?: ?[^\t\n\r ]+|[\t\n\r ]+(?![^\t\n\r ])|[\t\n\r ]+)")


class ByteMerges:
    """Merge ranks of a byte-level vocabulary, and counts of pieces under them."""

    def __init__(self, vocabulary: str, remembered: int = REMEMBERED_PIECES):
        with open(tokenizer_path(vocabulary), encoding="utf-8") as f:
            spec = json.load(f)
        names: dict[str, int] = {s: i for i, s in enumerate(byte_symbols())}
        #: Of each pair of symbols, packed into one number: its rank; of each rank: the joined symbol.
        self.rank: dict[int, int] = {}
        self.joined: list[int] = []
        for merge in spec["model"]["merges"]:
            left, right = (names.setdefault(x, len(names)) for x in (merge if isinstance(merge, list) else merge.split(" ")))
            text = "".join(merge) if isinstance(merge, list) else merge.replace(" ", "", 1)
            self.rank.setdefault(left << 24 | right, len(self.joined))
            self.joined.append(names.setdefault(text, len(names)))
        #: Special strings are one token each and split the text around them.
        special = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.special = re.compile("|".join(map(re.escape, special))) if special else None
        self.general = None
        self.remembered = remembered
        self.chunks: dict[str, int] = Remembered(lambda chunk: sum(map(self.counts.__getitem__, _PLAIN_PIECES.findall(chunk))))
        self.counts: dict[str, int] = Remembered(lambda piece: self.count_piece(piece.encode()))

    def count_piece(self, piece: bytes) -> int:
        """Tokens of one piece: its bytes less the merges."""
        n = len(piece)
        if n < 2:
            return n
        rank = self.rank.get
        symbols = [*piece, -1]  # the sentinel has no pair
        after, before = list(range(1, n + 2)), list(range(-1, n))
        heap = []  # rank and place in one number
        for i in range(n - 1):
            if (found := rank(symbols[i] << 24 | symbols[i + 1])) is not None:
                heap.append(found << 32 | i)
        heapify(heap)
        left = n
        while heap:
            entry = heappop(heap)
            i, order = entry & 0xFFFFFFFF, entry >> 32
            j = after[i]
            if rank(symbols[i] << 24 | symbols[j]) != order:
                continue  # one of the two has merged since this entry was pushed
            symbols[i], symbols[j] = joined, _ = self.joined[order], -1
            left -= 1
            k = after[i] = after[j]
            before[k] = i
            if (found := rank(joined << 24 | symbols[k])) is not None:
                heappush(heap, found << 32 | i)
            h = before[i]
            if h >= 0 and (found := rank(symbols[h] << 24 | joined)) is not None:
                heappush(heap, found << 32 | h)
        return left

    def _count(self, text: str) -> int:
        if not UNUSUAL.search(text):
            return sum(map(self.chunks.__getitem__, _PLAIN_CHUNKS.findall(text)))
        if self.general is None:
            import public_tokenizers
            import regex

            self.general = regex.compile(public_tokenizers.PATTERN)
        return sum(map(self.counts.__getitem__, self.general.findall(text)))

    def count(self, text: str) -> int:
        """Tokens of a text; special strings in it are one token each."""
        for known in (self.chunks, self.counts):
            if len(known) > self.remembered:
                known.clear()
        if self.special is None or not (found := self.special.findall(text)):
            return self._count(text)
        return len(found) + sum(map(self._count, self.special.split(text)))


_LOADED: dict[str, ByteMerges] = {}


def merges_of(vocabulary: str) -> ByteMerges:
    """This worker's merge table; loaded once per process."""
    if vocabulary not in _LOADED:
        _LOADED[vocabulary] = ByteMerges(vocabulary)
    return _LOADED[vocabulary]


def count_tokens(
    docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", limit: int = 512, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row. One pass, no shuffle."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merges = merges_of(vocabulary)
        for batch in batches:
            ids, bodies = batch.column(0), batch.column(1).to_pylist()
            n_bytes = pa.array([len(x) if x.isascii() else len(x.encode()) for x in bodies], pa.int64())
            n_tokens = pa.array([merges.count(x) for x in bodies], pa.int64())
            yield pa.RecordBatch.from_arrays([ids, n_bytes, n_tokens], ["doc_id", "n_bytes", "n_tokens"])

    counted = map_batches(texts(docs, id_col, text_col), work, "doc_id long, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > F.lit(limit))
