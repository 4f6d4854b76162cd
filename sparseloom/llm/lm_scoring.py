"""Log-bilinear language model, trained by noise-contrastive estimation, normalised exactly.

A token is predicted from the two before it: two context embeddings add up to a vector whose product with the
token's output embedding, plus a bias, is the token's log-weight. Each of the `hot` most frequent tokens has an output
embedding of its own. The others share some, by their last letter or their last letter beyond ASCII, and are told
apart below it by their smoothed training count. Probabilities are thus over every possible token: the
known ones, and one share for unknown tokens in each shared output. As context, the most frequent tokens
have embeddings of their own, and all others those of their spelling.

Training contrasts each token with tokens from the unigram noise distribution (shared
within a batch), all in numpy. The softmax is then normalised over all outputs for every pair of context classes: as the
log-weight is a sum, the sums of its exponentials are one matrix product, made in blocks of outputs.

What comes from the corpus covers all of it: token counts N and V, shared outputs and noise come
from the counts of every training document, and the gradient steps use every training token. Documents become
numbers once, are dealt to shards of about `SHARD_TOKENS` by a hash of id and text, and each shard learns from its documents
in hash order, a buffer at a time. The shards' parameters are averaged, in levels. A first round over some of the shards gives
all of them a common start, from which the second round learns from every token; partitioning changes nothing. Context classes grow in number with the corpus. Only the `hot` most frequent tokens (a
fixed number) go out to the workers; counts of the others are joined by token.

Defined results: null and empty texts are one end token; repeated rows each give a row; a null
doc_id stays null and is in the fold of the empty string; without training documents all
tokens are unknown (N = V = 0) and both scores are that of an empty model; an empty table gives no
rows; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, fold, map_batches, texts

FOLDS = 7
HELD_OUT_FOLD = 2
HOT = 60_000
#: Context classes of their own for a corpus of up to `GROWS_FROM` training tokens; beyond, they grow with its sixth root.
OWN_CLASSES = 700
GROWS_FROM = 1_000_000
DIMENSIONS = 40
SHARD_TOKENS = 8_000_000
#: Tokens that are brought into random order together, tokens of one gradient step, and noise tokens that the step shares.
BUFFER_TOKENS = 1 << 18
STEP_TOKENS = 2048
SHARED_NOISE = 64
#: Shards whose parameters one task averages, and parameters in one row on their way.
FAN_IN = 8
PIECE = 1 << 18
#: The first round is a start for all: one in so many shards learns.
START_SHARE = 8
#: The end of a text. No token can be equal to it, as tokens hold no blank.
END = b" "
_COUNTED_AT_ONCE = 300_000


def tokens(text: str) -> list[bytes]:
    """Lower-cased (A-Z) words split at ASCII white space, then the end token."""
    return [*text.encode("utf-8", "replace").lower().split(), END]


#: Classes of tokens by spelling: by the last letter, or the last letter beyond ASCII.
_ENDINGS = 27
_WIDE = 24
SHARED_CLASSES = _ENDINGS + _WIDE


def shared_class(token: bytes) -> int:
    """0 .. SHARED_CLASSES-1, from the token's spelling alone."""
    if not token.isascii():
        wide = [c for c in token.decode("utf-8", "replace") if c > "\x7f"]
        return _ENDINGS + ord(wide[-1]) % _WIDE
    last = token[-1]
    if 0x61 <= last <= 0x7A:
        return last - 0x60
    stem = token.rstrip(b".,;:!?\"')]}|*#$%&")
    return stem[-1] - 0x60 if stem and 0x61 <= stem[-1] <= 0x7A else 0


def count_training_tokens(docs: DataFrame) -> DataFrame:
    """token (binary), shared (its class by spelling), n: over every training document."""
    kinds = [pa.binary(), pa.int32(), pa.int64()]

    def rows(counts: Counter) -> pa.RecordBatch:
        columns = list(counts), [shared_class(t) for t in counts], list(counts.values())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], ["token", "shared", "n"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: Counter = Counter()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                counts.update(tokens(text))
                if len(counts) > _COUNTED_AT_ONCE:
                    yield rows(counts)
                    counts = Counter()
        yield rows(counts)

    training = docs.where(fold(F.col("doc_id"), FOLDS) != HELD_OUT_FOLD).select("text")
    partial = map_batches(training, work, "token binary, shared int, n long")
    return partial.groupBy("token", "shared").agg(F.sum("n").alias("n"))


@dataclass(frozen=True)
class Vocabulary:
    """The hot tokens with their counts, and what the other tokens of each spelling class come to."""

    hot: dict[bytes, int]
    counts: np.ndarray  # of each hot token
    own: int  # the first `own` hot tokens are context classes of their own
    contexts: np.ndarray  # context class of each output
    total: int
    distinct: int
    rare_tokens: np.ndarray  # by spelling class: training tokens that are not hot
    rare_distinct: np.ndarray

    @property
    def n_contexts(self) -> int:
        """Context classes; the number itself stands for the context before a text."""
        return self.own + SHARED_CLASSES

    def output_tokens(self) -> np.ndarray:
        """Training tokens of each output: hot tokens first, then spelling classes."""
        return np.concatenate([self.counts, self.rare_tokens])

    def lookup(self) -> _Lookup:
        found = _Lookup(self.hot)
        found.first_shared = len(self.hot)
        return found


class _Lookup(dict):
    """Outputs of tokens."""

    first_shared = 0

    def __missing__(self, token: bytes) -> int:
        return self.first_shared + shared_class(token)


def grown_classes(total: int) -> int:
    """Context classes of their own for a corpus of `total` training tokens. Tables have their square in entries."""
    return int(OWN_CLASSES * max(1.0, total / GROWS_FROM) ** (1 / 6))


def vocabulary(counted: DataFrame, hot: int = HOT, own_classes: int | None = None) -> Vocabulary:
    """Read the fixed-size parts of the counts: totals, spelling classes, the most frequent tokens."""
    sizes = counted.groupBy("shared").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")).collect()
    top = _most_frequent(counted, hot)
    words, counts = top.column("token").to_pylist(), top.column("n").to_numpy().astype(np.int64)
    total, distinct = sum(r["n"] for r in sizes), sum(r["v"] for r in sizes)
    own = min(grown_classes(total) if own_classes is None else own_classes, len(words))
    shared = top.column("shared").to_numpy().astype(np.int64)
    contexts = np.concatenate([np.where(np.arange(len(words)) < own, np.arange(len(words)), own + shared), own + np.arange(SHARED_CLASSES)])
    n, v = np.zeros(SHARED_CLASSES, np.int64), np.zeros(SHARED_CLASSES, np.int64)
    for r in sizes:
        n[r["shared"]], v[r["shared"]] = r["n"], r["v"]
    np.subtract.at(n, shared, counts)
    np.subtract.at(v, shared, 1)
    return Vocabulary({w: i for i, w in enumerate(words)}, counts, own, contexts, total, distinct, n, v)


def _most_frequent(counted: DataFrame, hot: int) -> pa.Table:
    """Tokens above a count that at most `hot` tokens reach, most frequent first.

    The count comes from a histogram over logarithmic steps, so no task sorts more than it sends.
    """
    step = F.floor(F.log2("n") * 64).cast("int")
    sizes = counted.groupBy(step.alias("step")).agg(F.count(F.lit(1)).alias("v")).collect()  # at most 64 rows per doubling
    least, held = None, 0
    for r in sorted(sizes, key=lambda r: -r["step"]):
        held += r["v"]
        if held > hot:
            break
        least = r["step"]
    kept = counted.where(step >= least) if least is not None else counted.limit(0)
    return kept.select("token", "shared", "n").toArrow().sort_by([("n", "descending"), ("token", "ascending")])


def encode_training(docs: DataFrame, vocab: Vocabulary) -> DataFrame:
    """key (hash of id and text), n, outputs (32-bit numbers): every token of every training document."""
    sent = docs.sparkSession.sparkContext.broadcast(vocab)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lookup = sent.value.lookup().__getitem__
        for batch in batches:
            found = [np.fromiter(map(lookup, words := tokens(text)), np.int32, len(words)) for text in batch.column(1).to_pylist()]
            columns = batch.column(0), pa.array([len(x) for x in found], pa.int64()), pa.array([x.tobytes() for x in found], pa.binary())
            yield pa.RecordBatch.from_arrays(list(columns), ["key", "n", "outputs"])

    training = docs.where(fold(F.col("doc_id"), FOLDS) != HELD_OUT_FOLD).select(F.xxhash64("doc_id", "text").alias("key"), "text")
    return map_batches(training, work, "key long, n long, outputs binary")


def contexts_of(outputs: np.ndarray, starts: np.ndarray, classes: np.ndarray, outside: int) -> tuple[np.ndarray, np.ndarray]:
    """Context classes two before and one before each token of texts that begin at `starts`."""
    near = np.full(len(outputs), outside, np.int64)
    near[1:] = classes[outputs[:-1]]
    near[starts] = outside
    far = np.full(len(outputs), outside, np.int64)
    far[1:] = near[:-1]
    far[starts] = outside
    return far, near


@dataclass(frozen=True)
class LogBilinear:
    """Normalised log10-probabilities of outputs in pairs of context classes."""

    far: np.ndarray  # context class x dimension
    near: np.ndarray
    out: np.ndarray  # output x dimension
    bias: np.ndarray
    norm: np.ndarray  # context class x context class

    def log10(self, far: np.ndarray, near: np.ndarray, target: np.ndarray) -> np.ndarray:
        found = np.empty(len(target))
        for i in range(0, len(target), 8192):
            f, c, t = far[i : i + 8192], near[i : i + 8192], target[i : i + 8192]
            terms = self.far.take(f, 0)
            terms += self.near.take(c, 0)
            terms *= self.out.take(t, 0)
            found[i : i + 8192] = terms.sum(axis=1) + self.bias.take(t) - self.norm[f, c]
        return found / np.log(10.0)


def _sums(rows: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct row numbers, and the sum of `values` of each."""
    order = np.argsort(rows, kind="stable")
    ordered = rows.take(order)
    at = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
    return ordered[at], np.add.reduceat(values.take(order, 0), at)


class Learner:
    """Parameters, and steps of noise-contrastive estimation with AdaGrad on them (one rate for each embedding)."""

    def __init__(self, output_tokens: np.ndarray, n_contexts: int, dimensions: int = DIMENSIONS, seed: int = 11) -> None:
        rng, n = np.random.default_rng(seed), len(output_tokens)
        noise = (output_tokens + 1.0) / (output_tokens.sum() + n)
        self.upto, self.log_noise = np.cumsum(noise), np.log(noise).astype(np.float32)
        sizes = [(n_contexts + 1, dimensions), (n_contexts + 1, dimensions), (n, dimensions)]
        self.params = [*(rng.normal(0, 0.1, x).astype(np.float32) for x in sizes), self.log_noise[:, None].copy()]
        self.grown = [np.full(len(p), 1e-2, np.float32) for p in self.params]

    def state(self) -> np.ndarray:
        return np.concatenate([x.ravel() for x in (*self.params, *self.grown)])

    def restore(self, state: np.ndarray) -> None:
        at = 0
        for x in (*self.params, *self.grown):
            x[...] = state[at : at + x.size].reshape(x.shape)
            at += x.size

    def learn(self, far: np.ndarray, near: np.ndarray, target: np.ndarray, rng: np.random.Generator, noise_each: int = 20, rate: float = 0.15) -> None:
        """Steps over the tokens in random order."""
        order = rng.permutation(len(target))
        for at in range(0, len(order), STEP_TOKENS):
            i = order[at : at + STEP_TOKENS]
            self._step(far[i], near[i], target[i], rng, np.float32(noise_each), rate)

    def _step(self, f: np.ndarray, c: np.ndarray, t: np.ndarray, rng: np.random.Generator, each: np.float32, rate: float) -> None:
        far, near, out, bias = self.params
        context, own = far.take(f, 0), out.take(t, 0)
        context += near.take(c, 0)
        # the tokens themselves: told apart from noise by the difference of log-weight and log-noise
        odds = np.einsum("ij,ij->i", context, own) + bias[:, 0].take(t) - self.log_noise.take(t) - np.log(each)
        wrong = 1 / (1 + np.exp(odds))
        # noise tokens shared by the step, each counting for noise_each / SHARED_NOISE
        k = np.minimum(np.searchsorted(self.upto, rng.random(SHARED_NOISE) * self.upto[-1], side="right"), len(out) - 1)
        noise = out.take(k, 0)
        fake = context @ noise.T
        fake += bias[k, 0] - self.log_noise[k] - np.log(each)
        np.negative(fake, out=fake)
        np.exp(fake, out=fake)
        fake += 1
        np.divide(each / np.float32(SHARED_NOISE), fake, out=fake)
        size = np.float32(1 / np.sqrt(len(t)))
        own *= wrong[:, None]
        own -= fake @ noise
        own *= size
        g_context = own
        # the last column is the bias's
        rows = np.concatenate([np.column_stack([wrong[:, None] * context, wrong]), -np.column_stack([fake.T @ context, fake.sum(axis=0)])]) * size
        at, g = _sums(np.concatenate([t, k]), rows)
        short = np.uint16 if len(far) < 1 << 16 else np.int64  # short numbers sort faster
        for which, (at, g) in enumerate((_sums(f.astype(short), g_context), _sums(c.astype(short), g_context), (at, g[:, :-1]), (at, g[:, -1:]))):
            self.grown[which][at] += (g * g).mean(axis=1)
            self.params[which][at] += rate * g / np.sqrt(self.grown[which][at])[:, None]

    def normalised(self, block: int = 4096) -> LogBilinear:
        """Exact normalisation: sums over all outputs for every pair of context classes, in blocks of outputs."""
        far, near, out, bias = self.params
        total = np.zeros((len(far), len(near)))
        for at in range(0, len(out), block):
            part = out[at : at + block].T
            total += np.exp(far @ part) @ np.exp(near @ part + bias[at : at + block, 0]).T
        return LogBilinear(far, near, out, bias[:, 0].copy(), np.log(total).astype(np.float32))


def train(
    docs: DataFrame, vocab: Vocabulary, dimensions: int = DIMENSIONS, rounds: int = 2, seed: int = 11, shard_tokens: int = SHARD_TOKENS
) -> LogBilinear:
    """Rounds in which shards learn from the average of the last, some in the first and all in the others; then exact normalisation."""
    learner = Learner(vocab.output_tokens(), vocab.n_contexts, dimensions, seed)
    shards = max(1, -(-vocab.total // shard_tokens))
    dealt = encode_training(docs, vocab).withColumn("shard", F.pmod("key", F.lit(shards)))
    dealt = durable(dealt.repartition(shards, "shard").sortWithinPartitions("shard", "key", "outputs").select("shard", "outputs"))
    for turn in range(rounds):
        sent = docs.sparkSession.sparkContext.broadcast((vocab.output_tokens(), vocab.contexts, vocab.n_contexts, learner.state(), turn))

        def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sizes, classes, outside, state, now = sent.value
            own, shard, weight, held, size = Learner(sizes, outside, dimensions, seed), None, 0, [], 0
            rng = np.random.default_rng(seed)

            def use() -> None:
                nonlocal weight, held, size
                lengths = np.array([len(x) for x in held])
                outputs = np.concatenate(held)
                own.learn(*contexts_of(outputs, np.cumsum(lengths) - lengths, classes, outside), outputs, rng)
                weight, held, size = weight + len(outputs), [], 0

            for batch in batches:
                for s, raw in zip(batch.column(0).to_pylist(), batch.column(1)):  # sorted, so each shard is a run
                    if s != shard:
                        if held:
                            use()
                        if weight:
                            yield from _parameters(shard, weight, own.state())
                        own.restore(state)
                        shard, weight, rng = s, 0, np.random.default_rng([seed, now, s])
                    held.append(np.frombuffer(raw.as_buffer(), np.int32).copy())
                    size += len(held[-1])
                    if size >= BUFFER_TOKENS:
                        use()
            if held:
                use()
            if weight:
                yield from _parameters(shard, weight, own.state())

        some = dealt.where(F.col("shard") % START_SHARE == 0) if turn == 0 and rounds > 1 else dealt
        state = _average(map_batches(some, learn, _ROWS), shards, len(learner.state()))
        if state is not None:
            learner.restore(state)
        sent.unpersist()
    return learner.normalised()


_ROWS = "shard long, piece int, weight long, state binary"


def _parameters(shard: int, weight: int, state: np.ndarray, first: int = 0) -> Iterator[pa.RecordBatch]:
    for k, at in enumerate(range(0, len(state), PIECE), first):
        raw = state[at : at + PIECE].astype(np.float32).tobytes()
        columns = pa.array([shard], pa.int64()), pa.array([k], pa.int32()), pa.array([weight], pa.int64()), pa.array([raw], pa.binary())
        yield pa.RecordBatch.from_arrays(list(columns), ["shard", "piece", "weight", "state"])


def _average(learnt: DataFrame, shards: int, size: int) -> np.ndarray | None:
    """Weighted mean of the shards' states, in levels of `FAN_IN`, in order, so that it is the same every time; one state comes to the driver."""
    pieces = -(-size // PIECE)
    while shards > 1:
        shards = -(-shards // FAN_IN)
        part = learnt.withColumn("part", F.floor(F.col("shard") / FAN_IN).cast("long"))
        part = part.repartition(min(10_000, shards * pieces), "part", "piece").sortWithinPartitions("part", "piece", "shard")
        learnt = map_batches(part.select("part", "piece", "weight", "state"), _averaged, _ROWS)
    rows = sorted(learnt.collect(), key=lambda r: r["piece"])
    return np.concatenate([np.frombuffer(r["state"], np.float32) for r in rows]) if rows else None


def _averaged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for each run of equal `part` and `piece`: summed weight and mean state."""
    key, weight, total = None, 0, None
    for batch in batches:
        for p, k, w, raw in zip(*(batch.column(c) for c in range(4))):
            w, x = w.as_py(), np.frombuffer(raw.as_buffer(), np.float32) * float(w.as_py())
            if (p.as_py(), k.as_py()) != key:
                if key is not None:
                    yield from _parameters(key[0], weight, total / weight, key[1])
                key, weight, total = (p.as_py(), k.as_py()), 0, 0.0
            weight, total = weight + w, total + x
    if key is not None:
        yield from _parameters(key[0], weight, total / weight, key[1])


def score(docs: DataFrame, counted: DataFrame, vocab: Vocabulary, model: LogBilinear) -> DataFrame:
    """Every document's row of counts and scores. Rare tokens meet their counts in one join."""
    sent = docs.sparkSession.sparkContext.broadcast((vocab, model))
    names = ["row", "doc_id", "token", "times", "n_tokens", "n_known", "base", "score"]
    kinds = [pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64()]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        v, m = sent.value
        lookup, first_shared = v.lookup().__getitem__, len(v.hot)
        per_token = np.log10(v.total + v.distinct + 1.0)
        in_class = np.log10(v.rare_tokens + v.rare_distinct + 1.0)
        log_hot = np.log10(v.counts + 1.0)
        start = np.zeros(1, np.int64)
        row = TaskContext.get().partitionId() << 40
        for batch in batches:
            out: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                words = tokens(text)
                n = len(words)
                at = np.fromiter(map(lookup, words), np.int64, n)
                hot = at < first_shared
                known = at[hot]
                found = m.log10(*contexts_of(at, start, v.contexts, v.n_contexts), at).sum() - in_class[at[~hot] - first_shared].sum()
                base = log_hot[known].sum() - n * per_token
                rare = Counter([words[i] for i in np.flatnonzero(~hot).tolist()])
                # the document's own sums ride on its first rare token, or on a key that no token has
                token, times = rare.popitem() if rare else (b" %d" % row, 0)
                out.append((row, doc, token, times, n, len(known), base, found))
                out += [(row, doc, t, k, 0, 0, 0.0, 0.0) for t, k in rare.items()]
                row += 1
                if len(out) > 50_000:
                    yield _rows(out, names, kinds)
                    out = []
            yield _rows(out, names, kinds)

    parts = map_batches(docs, work, "row long, doc_id long, token binary, times long, n_tokens long, n_known long, base double, score double")
    joined = parts.join(counted.select("token", "n"), "token", "left")
    extra = F.coalesce(F.col("times") * F.log10(F.col("n") + F.lit(1.0)), F.lit(0.0))
    summed = joined.groupBy("row", "doc_id").agg(
        F.sum("n_tokens").alias("n_tokens"),
        F.sum(F.col("n_known") + F.when(F.col("n").isNotNull(), F.col("times")).otherwise(0)).alias("n_known"),
        F.sum(F.col("base") + extra).alias("base_score"),
        F.sum(F.col("score") + extra).alias("score"),
    )
    return summed.select(
        "doc_id", (fold(F.col("doc_id"), FOLDS) == HELD_OUT_FOLD).alias("held_out"), "n_tokens", "n_known",
        F.lit(vocab.total).cast("long").alias("train_tokens"), "base_score", "score",
    )


def _rows(out: list[tuple], names: list[str], kinds: list[pa.DataType]) -> pa.RecordBatch:
    columns = zip(*out) if out else [()] * len(kinds)
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, kinds)], names)


def score_documents(
    docs: DataFrame, hot: int = HOT, own_classes: int | None = None, id_col: str = "doc_id", text_col: str = "text", shard_tokens: int = SHARD_TOKENS
) -> DataFrame:
    """Count, train and score: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    rows = texts(docs, id_col, text_col)
    counted = durable(count_training_tokens(rows))
    vocab = vocabulary(counted, hot, own_classes)
    return score(rows, counted, vocab, train(rows, vocab, shard_tokens=shard_tokens))
