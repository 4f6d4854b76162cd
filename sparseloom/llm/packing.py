"""Best-fit packing of tokenised documents into sequences of a fixed length.

Planning works on the histogram of piece lengths, never on pieces: best fit decreasing
over (length, count) moves whole runs of equal pieces into whole runs of equally filled
sequences, so its work depends on the sequence length and not on the corpus. The plan is a
list of slot runs: "pieces of length L with rank r0 .. r0+n go to sequences s0 .. s0+n at
offset o". Pieces then take their slots by joining on their rank within their length.
Ranks need no task that sees a whole length: each piece is ranked within (input partition,
length), and a running sum over the per-partition counts gives each partition its base.

Defined results: null and empty texts are one piece holding only the separator; repeated rows
are packed as separate documents; a null doc_id stays null; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

import re
from bisect import bisect_left, insort
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Remembered, durable, map_batches, row_schema, texts, tokenizer_path
from .unicode_classes import LETTERS, NUMBERS, UNUSUAL, byte_symbols

MAX_LENGTH = 2048
SEPARATOR = 0
#: Words whose ids a worker remembers; beyond it, the memory is emptied and filled anew.
REMEMBERED_WORDS = 400_000

#: The vocabulary's own splitting rule, for the plain Latin range.
_PLAIN_WORDS = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{LETTERS}]+|[{NUMBERS}]|[^\\s{LETTERS}{NUMBERS}]+")


class WordIds:
    """Token ids by the tokenizers library, whose model is asked once for each recurring word.

    The vocabulary never merges across white space, nor across its pre-tokenised words, so the
    ids of a text are those of its words in order. Texts outside the plain Latin range, and
    texts holding a special string, are handed to the library whole.
    """

    def __init__(self, vocabulary: str, remembered: int = REMEMBERED_WORDS):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(tokenizer_path(vocabulary))
        self.model = self.tokenizer.model
        special = [re.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.special = re.compile("|".join(special)) if special else None
        self.remembered = remembered
        self.symbols = dict(enumerate(byte_symbols()))
        self.words: dict[str, bytes] = Remembered(self._split_word)
        self.pieces: dict[str, bytes] = Remembered(self._ask_piece)

    def encode(self, body: str) -> bytes:
        """The text's ids as little-endian unsigned 32-bit numbers."""
        if UNUSUAL.search(body) or self.special and self.special.search(body):
            ids = self.tokenizer.encode(body, add_special_tokens=False).ids
            return np.asarray(ids, "<u4").tobytes()
        for known in (self.words, self.pieces):
            if len(known) > self.remembered:
                known.clear()
        return b"".join(map(self.words.__getitem__, body.lower().split()))

    def _split_word(self, word: str) -> bytes:
        if word.isalpha():
            return self.pieces[word]
        return b"".join(map(self.pieces.__getitem__, _PLAIN_WORDS.findall(word)))

    def _ask_piece(self, piece: str) -> bytes:
        found = self.model.tokenize(piece.encode().decode("latin-1").translate(self.symbols))
        return b"".join([t.id.to_bytes(4, "little") for t in found])


_LOADED: dict[str, WordIds] = {}


def _word_ids(vocabulary: str) -> WordIds:
    if vocabulary not in _LOADED:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        _LOADED[vocabulary] = WordIds(vocabulary)
    return _LOADED[vocabulary]


def tokenize_pieces(
    docs: DataFrame, vocabulary: str = "word_bpe_49k.json", max_length: int = MAX_LENGTH, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, piece, start, length, ids (binary, 4 bytes an id), part (the input partition)."""
    step, tail = 4 * max_length, SEPARATOR.to_bytes(4, "little")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        words, part = _word_ids(vocabulary), TaskContext.get().partitionId()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                rows = batch.slice(at, 512)
                out: list[tuple] = []
                for doc, body in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist()):
                    ids = words.encode(body) + tail
                    out += [(doc, i, i * max_length, ids[i * step : (i + 1) * step]) for i in range(-(-len(ids) // step))]
                doc, piece, start, ids = zip(*out) if out else ((), (), (), ())
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(doc, pa.int64()), pa.array(piece, pa.int32()), pa.array(start, pa.int64()),
                        pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary()),
                        pa.array([part] * len(out), pa.int64()),
                    ],
                    ["doc_id", "piece", "start", "length", "ids", "part"],
                )

    return map_batches(
        texts(docs, id_col, text_col), work, "doc_id long, piece int, start long, length long, ids binary, part long"
    )


@dataclass(frozen=True)
class PackingPlan:
    """Slot runs, sorted by (length, rank)."""

    length: np.ndarray
    rank: np.ndarray
    count: np.ndarray
    sequence: np.ndarray
    offset: np.ndarray
    sequences: int

    def slots(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Sequence and offset of the piece with this rank among those of its length."""
        shift = np.int64(1) << np.int64(44)
        at = np.searchsorted(self.length * shift + self.rank, length * shift + rank, side="right") - 1
        return self.sequence[at] + (rank - self.rank[at]), self.offset[at]


def plan_packing(histogram: dict[int, int], max_length: int = MAX_LENGTH) -> PackingPlan:
    """Best fit decreasing over counts. Work and memory depend on `max_length` only."""
    runs: list[tuple[int, int, int, int, int]] = []
    room: dict[int, list[tuple[int, int]]] = {}  # free tokens -> runs of sequences (first, count)
    sizes: list[int] = []  # the free sizes that occur, ascending
    opened = 0

    def put(free: int, first: int, count: int) -> None:
        if free and count:
            if free not in room:
                room[free] = []
                insort(sizes, free)
            room[free].append((first, count))

    for length in sorted(histogram, reverse=True):
        if not 0 < length <= max_length:
            raise ValueError(f"piece of {length} tokens; 1 to {max_length} are allowed")
        left, rank = histogram[length], 0
        while left:
            at = bisect_left(sizes, length)
            if at < len(sizes):
                free = sizes[at]
                first, count = room[free].pop()
                if not room[free]:
                    del room[free], sizes[at]
                used = min(left, count)
                runs.append((length, rank, used, first, max_length - free))
                put(free, first + used, count - used)
                put(free - length, first, used)
                rank, left = rank + used, left - used
                continue
            each = min(max_length // length, left)
            count = left // each
            for i in range(each):
                runs.append((length, rank + i * count, count, opened, i * length))
            put(max_length - each * length, opened, count)
            opened, rank, left = opened + count, rank + each * count, left - each * count
    runs.sort()
    columns = np.array(runs, np.int64).reshape(-1, 5).T
    return PackingPlan(*columns, sequences=opened)


def pack_pieces(pieces: DataFrame, max_length: int = MAX_LENGTH) -> DataFrame:
    """Adds sequence_id and offset to pieces that have `length` and `part`.

    `pieces` is cut with a checkpoint first, as it is read twice: for the histogram and for
    the slots. Only the histogram (at most `max_length` rows) comes to the driver, and only the
    plan, whose size `max_length` bounds, goes out.
    """
    kept = durable(pieces)
    counts = kept.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n_part"))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("part", "length", F.coalesce(F.sum("n_part").over(before), F.lit(0)).alias("base"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n_part").alias("n")).collect()}
    plan = plan_packing(histogram, max_length)
    local = Window.partitionBy("part", "length").orderBy("doc_id", "piece")
    ranked = (
        kept.join(bases, ["part", "length"])
        .withColumn("rank", F.col("base") + F.row_number().over(local) - 1)
        .drop("part", "base")
    )
    names = ranked.columns
    sent = kept.sparkSession.sparkContext.broadcast(plan)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rank, length = (batch.column(names.index(c)).to_numpy() for c in ("rank", "length"))
            sequence, offset = sent.value.slots(length, rank)
            columns = [c for n, c in zip(names, batch.columns) if n != "rank"]
            yield pa.RecordBatch.from_arrays(
                [*columns, pa.array(sequence, pa.int64()), pa.array(offset, pa.int64())],
                [*(n for n in names if n != "rank"), "sequence_id", "offset"],
            )

    return map_batches(ranked, work, f"{row_schema(ranked.drop('rank'))}, sequence_id long, offset long")


def pack_documents(
    docs: DataFrame, vocabulary: str = "word_bpe_49k.json", max_length: int = MAX_LENGTH, keep_ids: bool = True,
    id_col: str = "doc_id", text_col: str = "text",
) -> DataFrame:
    """Every piece of every document with its place: doc_id, piece, start, length, ids (if kept), ids_crc32, sequence_id, offset."""
    pieces = tokenize_pieces(docs, vocabulary, max_length, id_col, text_col).withColumn("ids_crc32", F.crc32("ids"))
    return pack_pieces(pieces if keep_ids else pieces.drop("ids"), max_length)


def sequences(packed: DataFrame) -> DataFrame:
    """The training sequences themselves: sequence_id, n_tokens, ids (binary), doc_ids in order."""
    placed = F.array_sort(F.collect_list(F.struct("offset", "ids", "doc_id")))
    return (
        packed.groupBy("sequence_id").agg(F.sum("length").alias("n_tokens"), placed.alias("placed"))
        .select("sequence_id", "n_tokens", F.aggregate("placed", F.lit(b""), lambda a, p: F.concat(a, p["ids"])).alias("ids"), F.col("placed.doc_id").alias("doc_ids"))
    )
