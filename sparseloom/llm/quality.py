"""Quality classifier: Bradley-Terry ranking of documents by pairwise preferences.

A preference pair is a document marked good and one marked poor. The chance that the first is
preferred is the logistic function of the difference of their scores, and a score is linear in the
features, so the model is logistic regression on feature differences, without an intercept. The
pairs' gradient is summed over all pairs of a step. The scale that differences leave open is then
fixed by a score quantile: the raw score below which the labelled share of poor documents lies
is mapped to the decision threshold, by one logistic curve.

Features describe the text alone: how letters, marks, digits, upper case, repeats of lines and
words, word lengths and line lengths are mixed. Labels, language, source and id are not inputs.

Labels are read from rows in the training folds only. Fitting uses at most `max_labelled` of
them, chosen by a hash of the id, which bounds what comes to the driver; scoring reads
every text whole.

Defined results: null and empty texts have the features of the empty text and a score;
repeated rows each give a row; labels with null id or null mark, and labels of unknown
documents, are passed over; of contradicting labels of one document the larger counts, and of
repeated ids one row is learned from; without
both kinds of labels every score is 0.5; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, keep_rows, map_batches, texts

FOLDS = 5
HELD_OUT_FOLD = 0
MAX_LABELLED = 20_000
THRESHOLD = 0.3
#: Range of the hash that chooses labelled rows.
_ORDERS = 1 << 40

#: What a byte is: lower-case letter, upper-case letter, digit, blank, line end, sentence
#: mark, other mark, beyond ASCII. Fixed values.
_LOWER, _UPPER, _DIGIT, _BLANK, _LINE, _SENTENCE, _MARK, _WIDE = range(8)
_KIND = bytes(
    _WIDE if b > 0x7F
    else _LOWER if 0x61 <= b <= 0x7A
    else _UPPER if 0x41 <= b <= 0x5A
    else _DIGIT if 0x30 <= b <= 0x39
    else _LINE if b in b"\n\r"
    else _BLANK if b in b" \t\x0b\x0c"
    else _SENTENCE if b in b".,;:?'\"-"
    else _MARK
    for b in range(256)
)
_MARKS = b"!#$%&*|<>{}[]()=+/\\@^~_`"
_URL = re.compile(rb"https?://|www\.|@")


def features(text: str) -> list[float]:
    """Fixed-length description of a text; all values are bounded or logarithmic."""
    raw = text.encode("utf-8", "replace")
    n = max(1, len(raw))
    kinds = np.bincount(np.frombuffer(raw.translate(_KIND), np.uint8), minlength=8)
    words = raw.split()
    nw = max(1, len(words))
    seen = Counter(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words)) if words else np.zeros(1, np.int64)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    nl = max(1, len(lines))
    line_lengths = np.fromiter(map(len, lines), np.int64, len(lines)) if lines else np.zeros(1, np.int64)
    pairs = len(set(zip(words, words[1:])))
    top = max(seen.values(), default=0)
    squares = sum(c * c for c in seen.values())
    packed = len(zlib.compress(raw, 1))
    upper_words = sum(map(bytes.isupper, words))
    pure = sum(map(bytes.isalpha, words))
    out = [*(kinds / n), *(min(1.0, 20 * raw.count(m) / n) for m in (_MARKS[i : i + 1] for i in range(len(_MARKS))))]
    out += [
        np.log1p(len(words)) / 10, np.log1p(len(lines)) / 10, len(seen) / nw, pairs / nw, top / nw, np.sqrt(squares) / nw,
        min(30.0, lengths.mean()) / 10, min(30.0, lengths.std()) / 10, min(60, lengths.max()) / 30, (lengths == 1).sum() / nw,
        len(set(lines)) / nl, np.log1p(line_lengths.mean()) / 10, np.log1p(line_lengths.max()) / 10,
        packed / (n + 20), upper_words / nw, pure / nw, min(1.0, 50 * len(_URL.findall(raw)) / nw),
        float(not words), float(len(words) < 5), float(len(words) < 20),
    ]
    return out


@dataclass(frozen=True)
class Ranking:
    """Standardised linear scores and the curve that turns them into 0..1."""

    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    cut: float
    slope: float
    threshold: float

    def score(self, rows: np.ndarray) -> np.ndarray:
        if not self.weights.any():
            return np.full(len(rows), 0.5)
        raw = np.clip((rows - self.mean) / self.scale, -6, 6) @ self.weights
        at = self.slope * (raw - self.cut) + np.log(self.threshold / (1 - self.threshold))
        return 1 / (1 + np.exp(-np.clip(at, -40, 40)))


def fit(
    rows: np.ndarray, good: np.ndarray, threshold: float = THRESHOLD, steps: int = 600, pairs: int = 4096, rate: float = 0.05,
    decay: float = 1e-3, seed: int = 7,
) -> Ranking:
    """Learn scores from (good, poor) pairs, then set the cut at the poor share's quantile."""
    width = rows.shape[1] if rows.ndim == 2 else len(features(""))
    if not len(rows) or good.all() or not good.any():
        return Ranking(np.zeros(width), np.ones(width), np.zeros(width), 0.0, 1.0, threshold)
    mean, scale = rows.mean(axis=0), rows.std(axis=0) + 1e-6
    x = np.clip((rows - mean) / scale, -6, 6)
    better, worse = x[good], x[~good]
    rng = np.random.default_rng(seed)
    w, m, v = np.zeros(width), np.zeros(width), np.zeros(width)
    for step in range(1, steps + 1):
        apart = better[rng.integers(0, len(better), pairs)] - worse[rng.integers(0, len(worse), pairs)]
        gradient = -(apart / (1 + np.exp(np.clip(apart @ w, -40, 40)))[:, None]).mean(axis=0) + decay * w
        m, v = 0.9 * m + 0.1 * gradient, 0.999 * v + 0.001 * gradient**2
        w = w - rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    raw = x @ w
    # the threshold is the quantile of scores that leaves the labelled share of poor documents below
    # it, placed midway between the neighbours on either side
    cut = float(np.quantile(raw, (~good).mean(), method="midpoint"))
    spread = float(np.median(np.abs(raw - cut))) or 1.0
    return Ranking(mean, scale, w, cut, 4.0 / spread, threshold)


def train(
    docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED, label_col: str = "quality", id_col: str = "doc_id",
    text_col: str = "text", threshold: float = THRESHOLD, steps: int = 600,
) -> Ranking:
    """Fit on a bounded, hash-chosen set of labelled documents outside the held-out fold."""
    marked = labels.select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("mark"))
    marked = marked.where("doc_id IS NOT NULL AND mark IS NOT NULL").where(fold(F.col("doc_id"), FOLDS) != HELD_OUT_FOLD)
    marked = marked.groupBy("doc_id").agg(F.max("mark").alias("mark"))
    marked = marked.withColumn("order", F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(_ORDERS)))
    # all but a little over `max_labelled` leave before the sort, so that its last task stays small at any size
    reach = min(_ORDERS, int(_ORDERS * (1.1 * max_labelled + 1000) / max(1, marked.count())))
    chosen = marked.where(F.col("order") < reach).orderBy("order", "doc_id").limit(max_labelled).drop("order")
    pairs = texts(docs, id_col, text_col).join(F.broadcast(chosen), "doc_id")  # at most max_labelled rows of two numbers
    kind = pa.list_(pa.float64())

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = pa.array([features(x) for x in batch.column(1).to_pylist()], kind)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), rows], ["doc_id", "mark", "x"])

    found = map_batches(pairs.select("doc_id", "text", "mark"), work, "doc_id long, mark int, x array<double>")
    found = found.groupBy("doc_id", "mark").agg(F.min("x").alias("x"))  # at most one row of each id comes to the driver
    got = found.toArrow().sort_by("doc_id").combine_chunks()
    x = np.concatenate([c.flatten().to_numpy() for c in got.column("x").chunks] or [np.zeros(0)])
    return fit(x.reshape(got.num_rows, -1) if got.num_rows else np.zeros((0, len(features("")))), got.column("mark").to_numpy() == 1, threshold, steps)


def score(docs: DataFrame, model: Ranking, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bodies = batch.column(1).to_pylist()
            rows = np.array([features(x) for x in bodies], float).reshape(len(bodies), -1)
            scores = sent.value.score(rows) if bodies else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores, pa.float64())], ["doc_id", "score"])

    return map_batches(texts(docs, id_col, text_col), work, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, max_labelled: int = MAX_LABELLED) -> DataFrame:
    """doc_id, held_out, score, predicted for every document."""
    model = train(docs, labels, max_labelled, threshold=threshold)
    scored = score(docs, model)
    return scored.select(
        "doc_id", (fold(F.col("doc_id"), FOLDS) == HELD_OUT_FOLD).alias("held_out"), "score",
        (F.col("score") >= threshold).cast("int").alias("predicted"),
    )


def keep_good(docs: DataFrame, model: Ranking, text_col: str = "text") -> DataFrame:
    """The rows of documents whose score reaches the threshold, with all their columns."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def keep(bodies: list[str]) -> list[bool]:
        rows = np.array([features(x) for x in bodies], float).reshape(len(bodies), -1)
        return (sent.value.score(rows) >= sent.value.threshold).tolist()

    return keep_rows(docs, text_col, keep)
