"""Language identification with error-correcting output codes.

Each language has a codeword of bits. For each bit a binary classifier over hashed character n-grams is trained (logistic
regression in numpy); a text gets the language whose codeword is nearest under the exponential loss of the bit margins,
each bit weighted by how well its classifier did on rows kept out of the fit. If the best two codewords are nearly as near
as each other, the text is flagged as ambiguous.

The classifier is fitted on at most about `Settings.per_language` labelled texts of each language, and on `Settings.rows` of
all, picked by a hash of the row, of the `Settings.languages` most frequent labels. Those texts count whole: n-grams are
counted on the executors, and the driver gets the counts of the sample. Defined results: a text that is null or has no letter gets `und`, score 0, and is ambiguous;
empty texts are such; very long texts are counted whole, in blocks; repeated rows give repeated results; with no labelled
rows everything is `und`; an empty table gives an empty table; only the named columns are read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tauprobe.llm.arrow_kernels import labelled_sample, pack_sparse, run, unpack_sparse

UNKNOWN = "und"
_ASCII_LETTER = re.compile("[A-Za-z]")


@dataclass(frozen=True)
class Settings:
    buckets: int = 4096
    #: Labelled texts of a language used in the fit, at most about this many, and of all languages together.
    per_language: int = 1500
    rows: int = 12_000
    #: Labels that are learnt, the most frequent first: what a dirty column adds costs nothing.
    languages: int = 200
    extra_bits: int = 12
    steps: int = 150
    ridge: float = 1e-4
    #: A text is ambiguous if the best language's share of the weight is below this.
    sure: float = 0.5
    seed: int = 11


def code_matrix(n: int, extra_bits: int, seed: int) -> np.ndarray:
    """Codewords, one row of +1 and -1 for each of n languages.

    Up to seven languages get all different two-way splits; more get random columns, chosen for the largest least
    distance between codewords.
    """
    if n <= 1:
        return np.ones((n, 1))
    if n <= 7:
        splits = np.arange(1, 1 << (n - 1))
        return np.vstack([-np.ones(len(splits)), *(np.where(splits >> i & 1, 1.0, -1.0) for i in range(n - 1))])
    rng = np.random.default_rng(seed)
    bits = int(np.ceil(np.log2(n))) + extra_bits
    tries = [np.where(rng.random((n, bits)) < 0.5, 1.0, -1.0) for _ in range(200)]
    tries = [m for m in tries if (np.abs(m.sum(0)) < n).all()] or tries
    return max(tries, key=lambda m: (bits - (m @ m.T - 2 * bits * np.eye(n)).max()) / 2)


def has_letter(text: str) -> bool:
    return bool(_ASCII_LETTER.search(text)) or any(map(str.isalpha, text))


def gram_counts(texts: list[str], buckets: int, block: int = 1 << 19) -> np.ndarray:
    """Counts of hashed byte 2- and 3-grams of case-folded texts, a row for each; grams that hold digits or signs share few buckets."""
    out = np.zeros((len(texts), buckets), np.float32)
    mask = np.uint32(buckets - 1)

    def add(first: int, joined: bytes, owner: np.ndarray, rows: int) -> None:
        b = _FOLD[np.frombuffer(joined, np.uint8)]
        if len(b) < 3:
            return
        pair = b[:-1] * np.uint32(61) + b[1:]
        key = owner[:-2] * np.int64(buckets)
        for h in (pair[:-1] * np.uint32(2654435761) >> np.uint32(7), (pair[:-1] * np.uint32(257) + b[2:]) * np.uint32(2246822519) >> np.uint32(9)):
            out[first : first + rows] += np.bincount(key + (h & mask), minlength=rows * buckets).reshape(rows, buckets)

    parts, first, size = [], 0, 0
    for i, text in enumerate(texts):
        data = b"  " + text.lower().encode() + b"  "
        if len(data) > block:
            for at in range(0, len(data) - 2, block):  # overlapping by two bytes, so that no gram is lost or counted twice
                piece = data[at : at + block + 2]
                add(i, piece, np.zeros(len(piece), np.int64), 1)
            data = b""
        parts.append(data)
        size += len(data)
        if size > block or len(parts) == 64 or i + 1 == len(texts):
            add(first, b"".join(parts), np.repeat(np.arange(len(parts)), [len(p) for p in parts]), len(parts))
            parts, first, size = [], i + 1, 0
    return out


def _fold_table() -> np.ndarray:
    """Bytes to codes: letters and bytes of longer characters stay apart, white space, digits and signs are one code each."""
    table = np.full(256, 1, np.uint32)
    table[list(b" \t\n\r\x0b\x0c")] = 2
    table[list(b"0123456789")] = 3
    table[list(b"abcdefghijklmnopqrstuvwxyz")] = np.arange(4, 30)
    table[128:] = np.arange(30, 158)
    return table


_FOLD = _fold_table()


def scaled(counts: np.ndarray) -> np.ndarray:
    """Square roots of the counts, at unit length; in place."""
    np.sqrt(counts, out=counts)
    for lo in range(0, len(counts), 256):
        part = counts[lo : lo + 256]
        part /= np.maximum(np.linalg.norm(part, axis=1, keepdims=True), 1e-9)
    return counts


def fit_bits(x: np.ndarray, targets: np.ndarray, steps: int, ridge: float) -> tuple[np.ndarray, np.ndarray]:
    """Logistic regressions for all bits at once, by accelerated gradient descent; targets are +1 and -1."""
    w, b = np.zeros((x.shape[1], targets.shape[1]), np.float32), np.zeros(targets.shape[1], np.float32)
    look_w, look_b, t = w.copy(), b.copy(), 1.0
    rate = 4.0  # inverse of the loss's curvature: rows have unit length, the logistic function's slope is a quarter at most
    for _ in range(steps):
        p = -targets / (1 + np.exp(np.clip(targets * (x @ look_w + look_b), -30, 30)))
        new_w = look_w - rate * len(x) * (x.T @ p / len(x) + ridge * look_w) / max(1.0, len(x) ** 0.5)
        new_b = look_b - rate * p.mean(0)
        new_t = (1 + (1 + 4 * t * t) ** 0.5) / 2
        look_w, look_b = new_w + (t - 1) / new_t * (new_w - w), new_b + (t - 1) / new_t * (new_b - b)
        w, b, t = new_w, new_b, new_t
    return w, b


@dataclass(frozen=True)
class Model:
    names: tuple[str, ...]
    codes: np.ndarray
    weights: np.ndarray
    bias: np.ndarray
    bit_weights: np.ndarray
    settings: Settings

    def scores(self, texts: list[str]) -> np.ndarray:
        """Shares of the languages for each text; they add up to 1."""
        margins = scaled(gram_counts(texts, self.settings.buckets)) @ self.weights + self.bias
        loss = np.exp(-np.clip(margins[:, None, :] * self.codes[None], -20, 20)) @ self.bit_weights
        share = 1 / np.maximum(loss, 1e-12) ** 2
        return share / share.sum(1, keepdims=True)

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, bool]]:
        """(language, score, ambiguous) of each text."""
        out = [(UNKNOWN, 0.0, True)] * len(texts)
        at = [i for i, t in enumerate(texts) if t and has_letter(t)]
        if self.names and at:
            for lo in range(0, len(at), 64):
                few = at[lo : lo + 64]
                for i, share in zip(few, self.scores([texts[i] for i in few]), strict=True):
                    best = int(share.argmax())
                    out[i] = self.names[best], float(share[best]), bool(share[best] < self.settings.sure)
        return out


def learn(texts: list[str], langs: list[str], settings: Settings = Settings()) -> Model:
    """Fits a model on texts."""
    order = fit_order(len(texts))
    counts = np.zeros((len(texts), settings.buckets), np.float32)
    for lo in range(0, len(texts), 64):
        counts[lo : lo + 64] = gram_counts([texts[i] for i in order[lo : lo + 64]], settings.buckets)
    return fit(counts, [langs[i] for i in order], settings)


def fit_order(n: int) -> list[int]:
    """Places of n rows with every fifth at the end: those are kept out to weight the bits, without a copy of the others."""
    return sorted(range(n), key=lambda i: i % 5 == 4)


def fit(counts: np.ndarray, langs: list[str], settings: Settings) -> Model:
    """Fits the bit classifiers on rows of counts, in the order of fit_order; the counts' memory is used."""
    names = tuple(sorted(set(langs)))
    codes = code_matrix(len(names), settings.extra_bits, settings.seed)
    if not names:
        return Model(names, codes, np.zeros((settings.buckets, 1), np.float32), np.zeros(1, np.float32), np.ones(1), settings)
    x = scaled(counts)
    targets = codes[np.searchsorted(names, langs)].astype(np.float32)
    kept = len(langs) - len(langs) // 5
    weights = np.ones(codes.shape[1])
    if kept < len(langs):
        w, b = fit_bits(x[:kept], targets[:kept], settings.steps, settings.ridge)
        wrong = ((np.sign(x[kept:] @ w + b) != targets[kept:]).sum(0) + 0.5) / (len(langs) - kept + 1)
        weights = np.maximum(np.log((1 - wrong) / wrong), 1e-3)
    w, b = fit_bits(x, targets, settings.steps, settings.ridge)
    return Model(names, codes, w, b, weights / weights.sum(), settings)


def train(df: DataFrame, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", learn_from: Column | None = None, settings: Settings = Settings()) -> Model:
    """Fits a model on a bounded sample of the labelled rows that satisfy learn_from; its texts are counted on the executors."""
    picked = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang"), (F.lit(True) if learn_from is None else learn_from).alias("use"))
    known = picked.where("use and lang is not null and text is not null").select("id", "text", "lang")
    few = labelled_sample(known, "lang", settings.per_language, settings.languages, settings.rows)
    if few is None:
        return learn([], [], settings)

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = batch.column(2).to_pylist()
        counts = gram_counts(texts, settings.buckets)
        grams = [pack_sparse(at := np.flatnonzero(x), x[at]) if has_letter(t) else None for t, x in zip(texts, counts, strict=True)]
        return pa.RecordBatch.from_arrays([*batch.columns[:2], batch.column(3), pa.array(grams, pa.binary())], ["id", "h", "lang", "grams"])

    kind = few.schema["id"].dataType.simpleString()
    rows = run(few.select("id", "h", "text", "lang"), [step], f"id {kind}, h bigint, lang string, grams binary").where("grams is not null").collect()  # settings.rows at most
    rows.sort(key=lambda r: (r.id is not None, r.id, r.h))
    rows = [rows[i] for i in fit_order(len(rows))]
    langs, counts = [r.lang for r in rows], np.zeros((len(rows), settings.buckets), np.float32)
    for x in counts[::-1]:
        at, n = unpack_sparse(bytes(rows.pop().grams))
        x[at] = n
    return fit(counts, langs, settings)


def predict(df: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, lang_pred, score, ambiguous): one for each row of df."""
    picked = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    shared = df.sparkSession.sparkContext.broadcast(model)  # its size is fixed by the settings and the number of languages

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        names, scores, unsure = zip(*shared.value.predict(batch.column(1).to_pylist()), strict=True) if batch.num_rows else ((), (), ())
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(unsure, pa.bool_())], ["id", "lang_pred", "score", "ambiguous"])

    return run(picked, [step], f"id {picked.schema['id'].dataType.simpleString()}, lang_pred string, score double, ambiguous boolean")
