"""Quality classifier: supervised subword embeddings.

A document is the average of the learned vectors of its features, which are hashed into a fixed table: words, pairs of
neighbouring words, and the character n-grams of words. A softmax over the average gives the probability of each label.
Vectors and output weights are trained together in numpy by stochastic gradient descent over documents.

Since the softmax has two labels and the average is linear, a feature's whole effect on the score is one number, its
vector times the difference of the output weights. Scoring looks these numbers up, vectorised over a block of text.

The classifier is fitted on at most about `Settings.per_label` labelled texts of each label, picked by a hash of the row;
they count whole, and their features are counted on the executors.
Defined results: a null text counts as empty; a text without features, such as an empty one, gets the score of the
training labels' shares; very long texts count whole, in blocks whose features add up to those of the text; repeated rows give repeated results; of
a repeated label the lowest counts; without labels, or with one label only, every score is that label's share, or 0.5; an
empty table gives an empty table; only the named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tauprobe.llm.arrow_kernels import labelled_sample, pack_sparse, run, segments, unpack_sparse


@dataclass(frozen=True)
class Settings:
    buckets: int = 1 << 16
    width: int = 8
    gram: int = 3
    #: Labelled texts of a label used in the fit, at most about this many.
    per_label: int = 3000
    rounds: int = 12
    rate: float = 0.5
    seed: int = 3


def features(text: str, settings: Settings) -> np.ndarray:
    """Numbers of the features of a text, repeats included.

    Hashes of stretches of bytes are differences of one running sum of byte times odd power, moved to a common power, so
    that words of any length are hashed at once.
    """
    b = np.frombuffer(b" " + text.encode() + b" ", np.uint8)
    blank = (b == 32) | ((b >= 9) & (b <= 13))
    edge = np.flatnonzero(np.diff(blank.view(np.int8)))
    starts, ends = edge[::2] + 1, edge[1::2] + 1
    if not len(starts):
        return np.zeros(0, np.int64)
    power, inverse = _powers(len(b) + 1)
    sums = np.concatenate(([np.uint64(0)], np.cumsum((b.astype(np.uint64) + np.uint64(1)) * power[: len(b)], dtype=np.uint64)))

    def hashed(a: np.ndarray, z: np.ndarray, salt: int) -> np.ndarray:
        h = (sums[z] - sums[a]) * inverse[a] + np.uint64(salt)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        return (h >> np.uint64(40)).astype(np.int64) & (settings.buckets - 1)

    at = np.arange(max(0, len(b) - settings.gram + 1))
    for k in range(1, settings.gram - 1):  # only the outer bytes may be blank, so that grams tell where words begin and end
        at = at[~blank[at + k]]
    return np.concatenate([hashed(starts, ends, 1), hashed(starts[:-1], ends[1:], 2), hashed(at, at + settings.gram, 3)])


_POWER = np.ones(1, np.uint64), np.ones(1, np.uint64)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse, modulo 2**64."""
    global _POWER
    if len(_POWER[0]) < n:
        n = 1 << n.bit_length()
        odd = 0x9E3779B97F4A7C15
        one = np.ones(1, np.uint64)
        _POWER = tuple(np.cumprod(np.concatenate((one, np.full(n, x, np.uint64))), dtype=np.uint64) for x in (odd, pow(odd, -1, 1 << 64)))
    return _POWER


def blocks(text: str, settings: Settings, size: int = 1 << 19) -> Iterator[tuple[np.ndarray, int]]:
    """(features, sign) of a text in blocks: signed, they add up to the features of the whole text.

    A block begins with the last word of the one before, so that what lies across the cut is met, and that word's own
    features are taken off again.
    """
    last = ""
    for part in segments(text, size):
        yield features(last + part, settings), 1
        if last:
            yield features(last, settings), -1
        words = part.encode().rsplit(None, 1)
        last = words[-1].decode() if words and len(part) < len(text) else ""


def counted(text: str, settings: Settings) -> tuple[np.ndarray, np.ndarray]:
    """The distinct features of a whole text and how often each occurs."""
    each = [(np.unique(at, return_counts=True), sign) for at, sign in blocks(text, settings)]
    if len(each) == 1:
        return each[0][0]
    total = np.zeros(settings.buckets, np.int64)
    for (at, n), sign in each:
        total[at] += sign * n
    at = np.flatnonzero(total)
    return at, total[at]


@dataclass(frozen=True)
class Model:
    effect: np.ndarray  # what each feature adds to the log-odds of label 1, were it the only one
    bias: float
    settings: Settings

    def score(self, text: str | None) -> float:
        total, n = 0.0, 0
        for at, sign in blocks(text or "", self.settings):
            total, n = total + sign * float(self.effect[at].sum()), n + sign * len(at)
        return float(1 / (1 + np.exp(-np.clip(total / max(n, 1) + self.bias, -30, 30))))


def learn(texts: list[str], labels: list[int], settings: Settings = Settings()) -> Model:
    """Fits a model on texts."""
    return fit([counted(t, settings) for t in texts], labels, settings)


def fit(found: list[tuple[np.ndarray, np.ndarray]], labels: list[int], settings: Settings) -> Model:
    """Vectors and output weights by gradient descent, a document at a time; labels are 0 and 1."""
    share = (sum(labels) + 0.5) / (len(labels) + 1)
    prior = float(np.log(share / (1 - share)))
    if len(set(labels)) < 2:
        return Model(np.zeros(settings.buckets, np.float32), prior, settings)
    rng = np.random.default_rng(settings.seed)
    vectors = rng.uniform(-1 / settings.width, 1 / settings.width, (settings.buckets, settings.width)).astype(np.float32)
    output = np.zeros((2, settings.width), np.float32)
    found = [(at, (n / max(n.sum(), 1)).astype(np.float32)) for at, n in found]
    steps, done = settings.rounds * len(found), 0
    bias = np.array([0.0, prior], np.float32)
    for _ in range(settings.rounds):
        for i in rng.permutation(len(found)):
            at, weight = found[i]
            rate = settings.rate * (1 - done / steps)
            done += 1
            if not len(at):
                continue
            mean = weight @ vectors[at]
            raw = output @ mean + bias
            p = np.exp(raw - raw.max())
            p /= p.sum()
            p[labels[i]] -= 1
            back = p @ output
            output -= rate * np.outer(p, mean)
            # a vector's step is as large as if it were the whole document, scaled by its share of the largest
            vectors[at] -= rate * (weight / weight.max())[:, None] * back
    return Model(vectors @ (output[1] - output[0]), float(bias[1] - bias[0]), settings)


def train(df: DataFrame, labels: DataFrame, learn_from: Column | None = None, id_col: str = "doc_id", text_col: str = "text", label_id: str = "doc_id", label_col: str = "quality", settings: Settings = Settings()) -> Model:
    """Fits a model on a bounded sample of the labelled rows; learn_from is a condition on the labels' columns."""
    known = labels if learn_from is None else labels.where(learn_from)
    known = known.select(F.col(label_id).alias("id"), F.col(label_col).cast("int").alias("label")).where("id is not null and label in (0, 1)").groupBy("id").agg(F.min("label").alias("label"))
    counts = {r.label: r["count"] for r in known.groupBy("label").count().collect()}
    if not counts:
        return learn([], [], settings)
    whole = 1 << 30
    bar = F.coalesce(*[F.when(F.col("label") == k, F.lit(min(whole, whole * settings.per_label // n))) for k, n in counts.items()])
    ids = known.where(F.pmod(F.xxhash64("id"), F.lit(whole)) < bar)  # bounded by per_label, so every task can hold them
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).where("text is not null").join(F.broadcast(ids), "id")
    few = labelled_sample(rows.select("id", "text", "label"), "label", settings.per_label, 2, 2 * settings.per_label)  # an id may have many rows
    if few is None:
        return learn([], [], settings)

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = [pack_sparse(*counted(t, settings)) for t in batch.column(2).to_pylist()]
        return pa.RecordBatch.from_arrays([*batch.columns[:2], batch.column(3), pa.array(found, pa.binary())], ["id", "h", "label", "found"])

    kind = few.schema["id"].dataType.simpleString()
    sent = run(few.select("id", "h", "text", "label"), [step], f"id {kind}, h bigint, label int, found binary").collect()  # bounded by per_label
    sent.sort(key=lambda r: (r.id, r.h))
    return fit([unpack_sparse(bytes(r.found)) for r in sent], [r.label for r in sent], settings)


def score(df: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, score, predicted): one for each row of df."""
    picked = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    shared = df.sparkSession.sparkContext.broadcast(model)  # a number for each bucket

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = np.array([shared.value.score(t) for t in batch.column(1).to_pylist()], np.float64)
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(found), pa.array((found >= 0.5).astype(np.int32))], ["id", "score", "predicted"])

    return run(picked, [step], f"id {picked.schema['id'].dataType.simpleString()}, score double, predicted int")
