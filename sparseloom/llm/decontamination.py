"""Benchmark decontamination with one Aho-Corasick automaton over normalised test items.

An item (question or answer) is lower-cased (A-Z), cut into words and turned into windows of
`window` consecutive words; an item with fewer words is one window. All windows of all items go
into one automaton whose symbols are words: a word of the benchmark is a pair of characters (so that no state
has more branches than the root of the vocabulary's size), any other word is a pair that occurs in no window.
A document is normalised the same way and scanned once; the end of every occurrence gives the document's word
numbers, and these the offsets in the original text.

The automaton has at most `MAX_STATES` states, which it reaches only with windows that share no beginnings. A benchmark
with more is cut between windows into blocks of that size. The plan is the same for any number of blocks: one stage, in which every
task takes its documents in chunks of `CHUNK_CHARS` and passes each chunk through the blocks in turn, with one automaton in memory
at a time; a lone automaton is built once per worker process.

Defined results: null and empty texts have no words and are clean; benchmark rows with null
id or text are passed over; repeated items count once; repeated documents each give a row; an
empty benchmark leaves every document clean; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import pickle
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, row_schema, texts

WINDOW = 10
#: States of one automaton (about 53 bytes each), and characters of the documents that pass through the blocks together.
MAX_STATES = 4_000_000
CHUNK_CHARS = 32_000_000

#: Bytes that end a word are everything ASCII but digits and letters.
_NORMAL = bytes(
    b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256)
)
_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def normal_words(text: str) -> list[bytes]:
    """Lower-cased words: runs of ASCII letters and digits and of anything beyond ASCII."""
    return text.encode("utf-8", "replace").translate(_NORMAL).split()


def windows_of(text: str, window: int) -> Iterator[tuple[bytes, ...]]:
    words = normal_words(text)
    for at in range(max(1, len(words) - window + 1) if words else 0):
        yield tuple(words[at : at + window])


class _Codes(dict):
    """Words of the benchmark by their pair of characters."""

    def __missing__(self, word: bytes) -> str:
        return "\0\0"


class WindowAutomaton:
    """Windows of items, as (item, words), found in one scan of a document."""

    def __init__(self, windows: list[tuple[str, tuple[bytes, ...]]]):
        import ahocorasick

        vocabulary = sorted({w for _, words in windows for w in words})
        side = math.isqrt(len(vocabulary)) + 1  # the two characters of a pair come from ranges of their own
        self.codes = _Codes((w, chr(1 + k // side) + chr(1 + side + k % side)) for k, w in enumerate(vocabulary))
        owners: dict[str, list[str]] = {}
        for item, words in windows:
            owners.setdefault("".join(map(self.codes.__getitem__, words)), []).append(item)
        self.automaton = ahocorasick.Automaton()
        for phrase, items in owners.items():
            self.automaton.add_word(phrase, (len(phrase) // 2, items))
        if owners:
            self.automaton.make_automaton()
        self.empty = not owners

    @property
    def states(self) -> int:
        return 0 if self.empty else self.automaton.get_stats()["nodes_count"]

    def scan(self, text: str) -> tuple[int, list[tuple[int, int]], set[str]]:
        """Number of words, hit runs of words [from, to), and the items found."""
        words = normal_words(text)
        if self.empty or not words:
            return len(words), [], set()
        found = [((end + 1) // 2, n, items) for end, (n, items) in self.automaton.iter("".join(map(self.codes.__getitem__, words)))]
        if not found:
            return len(words), [], set()
        change, items = np.zeros(len(words) + 1, np.int64), set()
        for end, n, of in found:
            change[end - n] += 1
            change[end] -= 1
            items.update(of)
        return len(words), _runs(change.cumsum()[:-1] > 0), items


def _runs(flags: np.ndarray) -> list[tuple[int, int]]:
    edges = np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]])))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist()))


def _joined(runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(runs):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def original_spans(text: str, runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Code-point offsets in the text of runs of its words."""
    raw = text.encode("utf-8", "replace").lower()
    at = [m.span() for m in _WORD.finditer(raw)]
    starts = np.flatnonzero((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)
    point = lambda byte: int(np.searchsorted(starts, byte))
    return [(point(at[a][0]), point(at[b - 1][1])) for a, b in runs]


_BUILT: dict[str, WindowAutomaton] = {}


class Blocks:
    """The benchmark's windows on their way to the workers: compressed blocks, each the size of one automaton."""

    def __init__(self, items: DataFrame, window: int, max_states: int):
        sc = items.sparkSession.sparkContext
        self.sent = []
        for block in _cut(items, window, max_states):
            raw = zlib.compress(pickle.dumps(block), 1)
            self.sent.append((hashlib.sha256(raw).hexdigest(), sc.broadcast(raw)))

    def scan(self, bodies: list[str]) -> list[tuple[int, list[tuple[int, int]], list[str]]]:
        """Number of words, hit runs and sorted items of each text."""
        out = [(0, [], [])] * len(bodies)
        for turn, (key, sent) in enumerate(self.sent or [("", None)]):
            if key not in _BUILT:
                _BUILT.clear()  # one automaton in memory at a time
                _BUILT[key] = WindowAutomaton(pickle.loads(zlib.decompress(sent.value)) if sent else [])
            for k, body in enumerate(bodies):
                n, runs, items = _BUILT[key].scan(body)
                if not turn:
                    out[k] = n, runs, sorted(items)
                elif runs:
                    out[k] = n, _joined([*out[k][1], *runs]), sorted({*out[k][2], *items})
        return out


def _cut(items: DataFrame, window: int, max_states: int) -> Iterator[list[tuple[str, tuple[bytes, ...]]]]:
    """Windows in blocks whose symbols, and so their states, are at most `max_states`; the driver holds one block at a time."""
    block: list[tuple[str, tuple[bytes, ...]]] = []
    symbols = 1
    for row in items.sort("item_id", "text").toLocalIterator():
        for words in windows_of(row["text"], window):
            if block and symbols + 2 * len(words) > max_states:
                yield block
                block, symbols = [], 1
            block.append((row["item_id"], words))
            symbols += 2 * len(words)
    if block:
        yield block


def _chunks(batches: Iterator[pa.RecordBatch], column: int) -> Iterator[pa.RecordBatch]:
    """The rows again, with about `CHUNK_CHARS` of text at a time."""
    held, size = [], 0
    for batch in batches:
        held.append(batch)
        size += batch.column(column).nbytes
        if size >= CHUNK_CHARS:
            yield pa.concat_batches(held)
            held, size = [], 0
    if held:
        yield pa.concat_batches(held)


def _items(benchmark: DataFrame, item_col: str, text_col: str) -> DataFrame:
    named = benchmark.select(F.col(item_col).cast("string").alias("item_id"), F.col(text_col).cast("string").alias("text"))
    return named.where("item_id IS NOT NULL AND text IS NOT NULL").distinct()


_SPAN = pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64())]))


def find_contamination(
    docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text",
    item_col: str = "item_id", item_text_col: str = "text", max_states: int = MAX_STATES,
) -> DataFrame:
    """doc_id, n_words, n_hit, items (sorted array), spans (array of from/to offsets in the text), n_items."""
    blocks = Blocks(_items(benchmark, item_col, item_text_col), window, max_states)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _chunks(batches, 1):
            bodies = batch.column(1).to_pylist()
            found = blocks.scan(bodies)
            spans = [[{"from": a, "to": b} for a, b in original_spans(text, runs)] if runs else [] for text, (_, runs, _) in zip(bodies, found)]
            columns = [
                batch.column(0), pa.array([n for n, _, _ in found], pa.int64()), pa.array([sum(b - a for a, b in runs) for _, runs, _ in found], pa.int64()),
                pa.array([items for _, _, items in found], pa.list_(pa.string())), pa.array(spans, _SPAN), pa.array([len(items) for _, _, items in found], pa.int64()),
            ]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_words", "n_hit", "items", "spans", "n_items"])

    schema = "doc_id long, n_words long, n_hit long, items array<string>, spans array<struct<`from`: long, `to`: long>>, n_items long"
    return map_batches(texts(docs, id_col, text_col), work, schema)


def keep_clean(
    docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, text_col: str = "text", item_col: str = "item_id",
    item_text_col: str = "text", max_states: int = MAX_STATES,
) -> DataFrame:
    """The rows, with all their columns, in whose texts no benchmark window occurs."""
    blocks = Blocks(_items(benchmark, item_col, item_text_col), window, max_states)
    at = docs.columns.index(text_col)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _chunks(batches, at):
            found = blocks.scan([x or "" for x in batch.column(at).to_pylist()])
            yield batch.filter(pa.array([not runs for _, runs, _ in found], pa.bool_()))

    return map_batches(docs, work, row_schema(docs))
