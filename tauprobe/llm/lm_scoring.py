"""Language-model scoring with a log-bilinear model trained by noise-contrastive estimation.

The model gives P(token | context) as P(class | context) times P(token | class). The class part is log-bilinear: the
vectors of the last few tokens, each weighted dimension by dimension, and the mean vector of a longer stretch make a
context vector, and its products with the class vectors, normalised over all classes, are the probabilities. The most
frequent tokens are classes of their own; the others share classes by their last bytes. Within a class a token has the
probability (c + 1/2) / (sum over the class of (c + 1/2), plus 1/2 for what training never had), with c its count in all
training texts. So every text has a normalised probability, whatever its words.

Input words and classes are chosen by the counts of all training texts, and the class part is trained in numpy on all of
them, whole: texts are written once as numbers, from which scores are made too (`fit_and_score`), and in each round every
partition trains the network it is sent on its own texts; the results, weighted by their tokens, are averaged for the next round. So the network depends a little on how
the texts are partitioned. Words are counted in Arrow batches before they are shuffled. The most frequent words' counts
go to the executors (`Settings.common`, a fixed number); for all other words the counts are joined, so none is left out.

Defined results: a null text counts as empty, and an empty text is one end token; very long texts count whole; repeated
rows each give a row; without training texts counts are zero and classes equally likely; an empty table gives an empty
table; only the named columns are read.
"""

from __future__ import annotations

import copy
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tauprobe.llm.arrow_kernels import give_back
from tauprobe.session import materialize

END = b""


@dataclass(frozen=True)
class Settings:
    #: Words whose counts every executor holds.
    common: int = 1 << 17
    inputs: int = 2000
    singles: int = 96
    suffixes: int = 128
    hashed: int = 32
    width: int = 16
    order: int = 3
    stretch: int = 16
    noise: int = 96
    batch: int = 512
    rounds: int = 4
    rate: float = 0.15
    seed: int = 5


def tokens(text: str | None) -> list[bytes]:
    """Words of a text in lower case (A-Z alone), and the end."""
    return [*(text or "").encode().lower().split(), END]


def split(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """The `tokens` of all texts, one after the other, as binary, and where each text's end."""
    marked = pc.binary_join_element_wise(pc.ascii_lower(pc.fill_null(texts.cast(pa.string()), "")), "", " ")  # so that an empty piece comes last, the end
    lists = pc.ascii_split_whitespace(marked)
    ends, pieces = lists.offsets.to_numpy()[1:] - lists.offsets[0].as_py(), lists.flatten()
    use = pc.binary_length(pieces).to_numpy(zero_copy_only=False) > 0
    use[ends - 1] = True
    return pieces.filter(pa.array(use)).cast(pa.binary()), np.cumsum(use)[ends - 1]


def parts(texts: pa.Array, most: int = 1 << 22) -> Iterator[pa.Array]:
    """Slices of about so many bytes; a text is never cut."""
    rows = max(1, most * len(texts) // max(texts.nbytes, 1))
    for lo in range(0, len(texts), rows):
        yield texts.slice(lo, rows)


@dataclass(frozen=True)
class Words:
    """The fixed maps from a token to its input number and its class."""

    inputs: dict[bytes, int]
    singles: dict[bytes, int]
    suffixes: dict[bytes, int]
    settings: Settings

    @property
    def classes(self) -> int:
        return self.settings.singles + self.settings.suffixes + self.settings.hashed

    def class_of(self, word: bytes) -> int:
        if (k := self.singles.get(word)) is None and (k := self.suffixes.get(word[-3:])) is None:
            k = self.settings.singles + self.settings.suffixes + zlib.crc32(word[-1:]) % self.settings.hashed
        return k

    def input_of(self, word: bytes) -> int:
        """0 stands for what is before the text; frequent words have their own numbers, others that of their class."""
        return self.inputs.get(word) or 1 + self.settings.inputs + self.class_of(word)

    def classes_of(self, words: pa.Array) -> np.ndarray:
        """class_of of each word that is no class of its own, from the last three bytes of all words at once."""
        bounds = np.frombuffer(words.buffers()[1], np.int32, len(words) + 1, 4 * words.offset) if len(words) else np.zeros(1, np.int32)
        data = np.frombuffer(words.buffers()[2], np.uint8) if bounds[-1] else np.zeros(1, np.uint8)
        ends, sizes = bounds[1:].astype(np.int64), np.diff(bounds)
        last = [np.where(sizes > j, data.take(ends - 1 - j, mode="clip"), 0).astype(np.int64) for j in range(3)]
        keys = np.minimum(sizes, 3).astype(np.int64) << 24 | last[2] << 16 | last[1] << 8 | last[0]
        known = sorted((len(e) << 24 | int.from_bytes(e), k) for e, k in self.suffixes.items())
        known, own = np.array([*known, (1 << 30, 0)], np.int64).T.copy()
        place = np.searchsorted(known, keys)
        hashed = np.array([zlib.crc32(bytes([b])) % self.settings.hashed for b in range(256)])[last[0]]
        hashed[sizes == 0] = zlib.crc32(b"") % self.settings.hashed
        return np.where(known[place] == keys, own[place], self.settings.singles + self.settings.suffixes + hashed)

    def numbering(self):
        """A function that gives input_of(word) << 12 | class_of(word), in one call for each word."""
        inputs, singles, suffixes, crc = self.inputs.get, self.singles.get, self.suffixes.get, zlib.crc32
        hashed, rest, other = self.settings.hashed, self.settings.singles + self.settings.suffixes, 1 + self.settings.inputs

        def number(word: bytes) -> int:
            if (k := singles(word)) is None and (k := suffixes(word[-3:])) is None:
                k = rest + crc(word[-1:]) % hashed
            return (inputs(word) or other + k) << 12 | k

        return number


def word_maps(counts: DataFrame, settings: Settings) -> Words:
    """The maps that the counts of all training tokens give; the driver gets as many rows as the settings say."""
    ranked = [bytes(r.word) for r in counts.orderBy(F.desc("c"), "word").limit(max(settings.inputs, settings.singles)).collect()]
    singles = {w: i for i, w in enumerate(ranked[: settings.singles])}
    alone = counts.sparkSession.createDataFrame([(bytearray(w),) for w in singles], "word binary")
    ends = counts.join(F.broadcast(alone), "word", "left_anti").groupBy(F.expr("substring(word, -3, 3)").alias("end")).agg(F.sum("c").alias("c"))
    best = [bytes(r.end) for r in ends.orderBy(F.desc("c"), "end").limit(settings.suffixes).collect()]
    suffixes = {e: settings.singles + i for i, e in enumerate(best)}
    return Words({w: 1 + i for i, w in enumerate(ranked[: settings.inputs])}, singles, suffixes, settings)


@dataclass
class Network:
    inputs: np.ndarray  # of tokens, a row each
    near: np.ndarray  # weights of the last tokens, by distance
    far: np.ndarray  # weights of the stretch
    outputs: np.ndarray  # of classes
    bias: np.ndarray

    def contexts(self, ids: np.ndarray, at: np.ndarray, stretch: int) -> np.ndarray:
        """Context vectors of the places `at`; each text in ids follows `stretch` zeros."""
        if len(ids) <= stretch:
            return np.zeros((len(at), len(self.far)), np.float32)
        vectors = self.inputs.take(ids, 0)
        h = _sums(vectors[1:], stretch)
        h *= self.far / np.float32(stretch)
        for j, weights in enumerate(self.near):
            h += vectors[stretch - j : len(ids) - j] * weights
        return h.take(at - 1 - stretch, 0)

    def log10_classes(self, h: np.ndarray, classes: np.ndarray) -> np.ndarray:
        """Normalised log10 probabilities of the classes, in blocks of batched products.

        Blocks are filled up to one size, and a place is shifted by itself, so that what a place gets, up to the last bit, does
        not depend on the places around it.
        """
        n, rows = len(h), np.arange(_SCORED)
        out = np.empty(-(-n // _SCORED) * _SCORED, np.float64)
        most = np.zeros(len(out), np.float32)
        most[:n] = np.sqrt((h * h).sum(1)) * np.sqrt((self.outputs * self.outputs).sum(1).max(initial=0)) + np.abs(self.bias).max(initial=0)
        weights = np.vstack([self.outputs.T, self.bias])
        h, short = np.ones((len(out), weights.shape[0]), np.float32), h
        h[:n, :-1], h[n:, :-1] = short, 0
        classes = np.append(classes, np.zeros(len(out) - n, np.int64))
        ones = np.ones(len(self.bias), np.float32)
        scores = np.empty((_SCORED, len(self.bias)), np.float32)
        for lo in range(0, len(h), _SCORED):
            block = slice(lo, lo + _SCORED)
            np.matmul(h[block], weights, out=scores)
            own = scores[rows, classes[block]]
            if (far := most[block] > 80).any():  # else no power overflows, and no row of them vanishes
                top = np.where(far, scores.max(1), np.float32(0))
                own -= top
                scores -= top[:, None]
            np.exp(scores, out=scores)
            out[block] = own - np.log(scores @ ones)
        return out[:n] / np.log(10)


#: Places whose classes are scored together, and whose contexts are made together, so that they stay in the processor's memory.
_SCORED, _PLACES = 512, 1 << 13


def padded(lists: list[np.ndarray], stretch: int) -> tuple[np.ndarray, np.ndarray]:
    """One array with 1 + stretch zeros before each list, and the places of the lists' own values."""
    gap = 1 + stretch
    ids = np.zeros(sum(map(len, lists)) + gap * len(lists), np.int64)
    at, to = [], 0
    for x in lists:
        to += gap
        ids[to : to + len(x)] = x
        at.append(np.arange(to, to + len(x)))
        to += len(x)
    return ids, np.concatenate(at) if at else np.zeros(0, np.int64)


_PARTS = ("inputs", "near", "far", "outputs", "bias")

#: Consecutive places of a batch that are worked off together, tokens that are shuffled together, batches that are laid out together,
#: and what marks places outside texts.
_RUN, _HELD, _LAID, _GAP = 32, 1 << 18, 128, 1 << 31


def start(words: Words, class_counts: np.ndarray) -> tuple[Network, dict[str, np.ndarray]]:
    """The network before training, and the sums of squared gradients."""
    s, rng = words.settings, np.random.default_rng(words.settings.seed)
    noise = _noise(class_counts)
    net = Network(
        rng.normal(0, 0.1, (1 + s.inputs + words.classes, s.width)).astype(np.float32), np.full((s.order, s.width), 1 / s.order, np.float32), np.ones(s.width, np.float32), rng.normal(0, 0.1, (words.classes, s.width)).astype(np.float32), np.log(noise).astype(np.float32)
    )
    net.inputs[0] = 0
    return net, {k: np.full_like(getattr(net, k), 1e-6) for k in _PARTS}


def _noise(class_counts: np.ndarray) -> np.ndarray:
    return (class_counts + 0.5) / (class_counts + 0.5).sum()


def _sure(x: np.ndarray) -> np.ndarray:
    """The logistic function of -x, in place."""
    np.exp(x, out=x)
    x += 1
    return np.divide(1, x, out=x)


def _rows_of(x: np.ndarray) -> np.ndarray:
    """A view of x whose items are its rows, which are put in place faster than their values."""
    return x.view(f"V{x.itemsize * x.shape[1]}").ravel()


def _sums(x: np.ndarray, n: int) -> np.ndarray:
    """Sums of n consecutive rows, from sums of 1, 2, 4 and so on."""
    rows, size, at, total = len(x) - n + 1, 1, 0, None
    while True:
        if n & size:
            part = x[at : at + rows]
            total, at = part if total is None else total + part, at + size
        if (size := 2 * size) > n:
            return total
        x = x[size // 2 :] + x[: -size // 2]


def improve(net: Network, past: dict[str, np.ndarray], lists: list[np.ndarray], noise: np.ndarray, s: Settings, rng: np.random.Generator) -> None:
    """One pass over texts, as numbers input << 12 | class, with noise shared by a batch, and steps scaled by past gradients.

    A batch has runs of consecutive places. Its vectors lie dimension by dimension, so that for each of them one product with a
    small matrix makes the contexts of all runs from what is before them, and two more give the gradients of both.
    A class that is drawn several times as noise is scored once and counts as often; of the inputs, only the rows that a
    batch met are touched. Biases are kept less the log of the noise.
    """
    gap, lengths = 1 + s.stretch, [len(x) for x in lists]
    width, n_classes, inner, each = s.width, len(noise), s.order + 1, max(1, s.batch // _RUN)
    n_runs = -(-(sum(lengths) + gap * len(lists) - s.stretch) // _RUN)
    n_batches = -(-n_runs // each)
    laid = np.full((n_runs + 1) * _RUN + s.stretch, _GAP, np.int64)  # the run after the last has no places
    laid[np.arange(sum(lengths)) + np.repeat(gap * np.arange(1, len(lists) + 1), lengths)] = np.concatenate(lists)
    n, n_before = _RUN * each, s.stretch + _RUN - 1
    places = laid[s.stretch :].reshape(-1, _RUN)
    in_text, own_classes = (places != _GAP).astype(np.float32), places & 0xFFF
    before = np.lib.stride_tricks.sliding_window_view(laid >> 12 & 0x7FFFF, n_before)[::_RUN]  # of all places of a run, and in the stretch before it
    order = np.append(rng.permutation(n_runs), np.full(n_batches * each - n_runs, n_runs)).reshape(-1, each)
    order = order[in_text.any(1)[order].any(1)]

    def steps() -> Iterator[tuple]:
        """Of each batch the places in texts, each place's share, classes, inputs of all places and those before, and half the noise's share."""
        for lo in range(0, len(order), _LAID):
            x = order[lo : lo + _LAID]
            used = in_text[x].reshape(-1, n)
            sizes = used.sum(1, keepdims=True)
            drawn = np.searchsorted(np.cumsum(noise), np.sort(rng.random((len(x), s.noise))), "right")  # in order they are found faster
            drawn = np.minimum(drawn, n_classes - 1) + n_classes * np.arange(len(x))[:, None]
            halves = np.bincount(drawn.ravel(), minlength=n_classes * len(x)).reshape(-1, n_classes).astype(np.float32)
            halves /= 2 * sizes
            yield from zip(used, used / sizes, own_classes[x].reshape(-1, n), before[x].reshape(-1, n_before * each), halves, strict=True)

    log_noise = np.log(noise * s.noise).astype(np.float32)
    seen, spot = np.zeros(len(net.inputs), bool), np.zeros(len(net.inputs), np.int64)
    numbers, cells = np.arange(n_before * each), np.arange(max(n_before * each, n_classes) * (width + 1))
    cells_in, cells_out = cells[: len(numbers) * width].reshape(-1, width), cells[: n_classes * (width + 1)].reshape(-1, width + 1)  # of rows

    def joined(near: np.ndarray, far: np.ndarray, outputs: np.ndarray, bias: np.ndarray) -> np.ndarray:
        return np.concatenate([near.ravel(), far, np.column_stack([outputs, bias]).ravel()])

    def taken_apart(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return x[: inner * width].reshape(inner, width), x[inner * width :].reshape(n_classes, width + 1)

    # all other values, and views of them: scales, of the last token first and of the stretch last, and classes, each with its bias last
    fixed, fixed_past = joined(net.near, net.far, net.outputs, net.bias - log_noise), joined(*(past[k] for k in _PARTS[1:]))
    g_fixed = np.empty_like(fixed)
    (scales, outputs), (g_scales, g_outputs) = taken_apart(fixed), taken_apart(g_fixed)
    whole, whole_past, classes = _rows_of(net.inputs), _rows_of(past["inputs"]), _rows_of(g_outputs)
    ones = np.ones(width + 1, np.float32)
    ahead = np.arange(n_before) - np.arange(_RUN)[:, None]
    reach = np.stack([*(ahead == s.stretch - 1 - j for j in range(s.order)), ((ahead >= 0) & (ahead < s.stretch)) / s.stretch]).astype(np.float32)  # of each scale, from what is before to the places of a run
    back_reach, reach = reach.reshape(inner, -1), reach.transpose(0, 2, 1).reshape(inner, -1)
    h = np.empty((width + 1, n), np.float32)  # contexts, filled anew by each batch; the last row goes with the bias
    contexts = h[:width].reshape(width, each, _RUN)

    with np.errstate(over="ignore"):  # a power beyond single precision makes a probability of zero, as it should
        for use, share, target, back, half in steps():
            vectors = net.inputs.take(back, 0).T.copy().reshape(width, each, n_before)
            np.matmul(vectors, (scales.T @ reach).reshape(width, n_before, _RUN), out=contexts)
            h[width] = 1
            h *= use
            own = outputs.take(target, 0).T.copy()
            up = _sure(ones @ (h * own))  # pulled towards the data
            up *= -share
            drawn = half.nonzero()[0]
            half = half.take(drawn)[:, None]
            noisy = outputs.take(drawn, 0)
            down = (noisy * np.float32(0.5)) @ h
            np.tanh(down, out=down)
            down += 1  # twice how much is pushed from the noise: the logistic function of x is (1 + tanh(x / 2)) / 2
            noisy *= half
            g_h = noisy[:, :width].T @ down
            g_h *= use
            own *= up
            g_h += own[:width]
            g_h = g_h.reshape(width, each, _RUN)
            pushed = down @ h.T
            pushed *= half
            h *= up
            g_outputs[:] = np.bincount(cells_out.take(target, 0).ravel(), h.T.astype(np.float64, order="C").ravel(), g_outputs.size).reshape(g_outputs.shape)
            pushed += g_outputs.take(drawn, 0)
            classes[drawn] = _rows_of(pushed)
            np.matmul(reach, (vectors.transpose(0, 2, 1) @ g_h).reshape(width, -1).T, out=g_scales)
            g_vectors = g_h @ (scales.T @ back_reach).reshape(width, _RUN, n_before)
            seen[back] = True
            met = seen.nonzero()[0]
            seen[met] = False
            spot[met] = numbers[: len(met)]
            g_in = np.bincount(cells_in.take(spot.take(back), 0).ravel(), g_vectors.reshape(width, -1).T.astype(np.float64, order="C").ravel(), len(met) * width).reshape(-1, width).astype(np.float32)
            if not met[0]:
                g_in[0] = 0  # what is before a text stays zero
            inputs, squares = net.inputs.take(met, 0), past["inputs"].take(met, 0)
            inputs -= _change(g_in, squares, s.rate)
            whole[met], whole_past[met] = _rows_of(inputs), _rows_of(squares)
            fixed -= _change(g_fixed, fixed_past, s.rate)

    for flat, to, more in ((fixed, {k: getattr(net, k) for k in _PARTS}, log_noise), (fixed_past, past, 0)):
        few, many = taken_apart(flat)
        to["near"][:], to["far"][:], to["outputs"][:], to["bias"][:] = few[:-1], few[-1], many[:, :width], many[:, width] + more


def _change(g: np.ndarray, squares: np.ndarray, rate: float) -> np.ndarray:
    """What a step takes off, from mean gradients, which are used up; the squares go on."""
    held = g * g
    squares += held
    g *= np.float32(rate)
    g /= np.sqrt(squares, out=held)
    return g


def train(written: DataFrame, words: Words, class_counts: np.ndarray) -> Network:
    """Noise-contrastive estimation over all texts (column numbers): in each round the average of the partitions' networks."""
    net, past = start(words, class_counts)
    s, noise = words.settings, _noise(class_counts)
    if not class_counts.sum():
        net.outputs[:], net.bias[:] = 0, 0
        return net
    context = written.sparkSession.sparkContext

    for round_ in range(s.rounds):
        sent = context.broadcast((net, past))

        def kernel(batches: Iterator[pa.RecordBatch], sent=sent, round_=round_) -> Iterator[pa.RecordBatch]:
            _SCORERS.clear()  # what numbered the texts in this process is not needed while it trains
            own, squares = copy.deepcopy(sent.value)
            rng = np.random.default_rng([s.seed, round_, TaskContext.get().partitionId()])
            held, n, seen = [], 0, 0
            for b in batches:
                for row in b.column(0):
                    held.append(np.frombuffer(row.as_buffer(), np.int32))
                    n += len(held[-1])
                    if n >= _HELD:
                        improve(own, squares, held, noise, s, rng)
                        held, n, seen = [], 0, seen + n
            if held:
                improve(own, squares, held, noise, s, rng)
            if seen + n:
                yield _row(_flat(own, squares), seen + n)
            give_back()

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            weight, total = 0, 0.0
            for b in batches:
                for flat, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    total, weight = total + n * np.frombuffer(flat), weight + n
            if weight:
                yield _row(total / weight, weight)

        trained = written.mapInArrow(kernel, "flat binary, n bigint").repartition(8).mapInArrow(add, "flat binary, n bigint").collect()  # eight at most
        flat = sum(r.n * np.frombuffer(r.flat) for r in trained) / sum(r.n for r in trained)
        at = 0
        for part in [(net, k) for k in _PARTS] + [(past, k) for k in _PARTS]:
            old = part[0][part[1]] if part[0] is past else getattr(net, part[1])
            old[...] = flat[at : at + old.size].reshape(old.shape)
            at += old.size
    return net


def _flat(net: Network, past: dict[str, np.ndarray]) -> np.ndarray:
    return np.concatenate([*(getattr(net, k).ravel() for k in _PARTS), *(past[k].ravel() for k in _PARTS)]).astype(np.float64)


def _row(flat: np.ndarray, n: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([flat.tobytes()], pa.binary()), pa.array([n], pa.int64())], ["flat", "n"])


@dataclass(frozen=True)
class Model:
    words: Words
    network: Network | None  # none before training
    counts: DataFrame  # word binary, c bigint: of all training tokens
    total: int
    distinct: int
    common: dict[bytes, int]
    class_log10: np.ndarray  # log10 of each class's sum


def count_tokens(texts: DataFrame, flush: int = 1 << 26) -> DataFrame:
    """Rows (word, c): counts of all tokens of column text; about `flush` bytes of tokens are counted together first."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Array] = []

        def batch() -> pa.RecordBatch:
            found = pa.chunked_array(held, pa.binary()).value_counts()
            return pa.RecordBatch.from_arrays([found.field(0), found.field(1)], ["word", "c"])

        for b in batches:
            for part in parts(b.column(0)):
                held.append(split(part)[0])
                if sum(x.nbytes for x in held) > flush:
                    yield batch()
                    held.clear()
        if held:
            yield batch()
        give_back()

    return texts.mapInArrow(kernel, "word binary, c bigint").groupBy("word").agg(F.sum("c").alias("c"))


def _most_common(counts: DataFrame, most: int) -> dict[bytes, int]:
    """The words of the highest counts, at most so many: those from a bin of counts on, eight bins an octave, so the driver gets nothing else."""
    bin_ = F.floor(8 * F.log2("c"))
    bar, held = None, 0
    for r in sorted(counts.groupBy(bin_.alias("bin")).count().collect(), key=lambda r: -r.bin):  # some hundred bins at most
        held += r["count"]
        if held > most:
            break
        bar = r.bin
    return {} if bar is None else {bytes(r.word): r.c for r in counts.where(bin_ >= bar).collect()}


def _rows(df: DataFrame, id_col: str, text_col: str, learn_from: Column | None = None) -> DataFrame:
    use = F.lit(True) if learn_from is None else F.coalesce(learn_from, F.lit(True))
    return df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), use.alias("use"))


def fit(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", learn_from: Column | None = None, settings: Settings = Settings()) -> Model:
    """Counts over all rows that satisfy learn_from, and a network trained on all of them."""
    rows = _rows(df, id_col, text_col, learn_from).where("use")
    model, class_counts = _counted(rows, settings)
    return replace(model, network=train(_encoded(rows, model).select("numbers"), model.words, class_counts))


def fit_and_score(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", learn_from: Column | None = None, settings: Settings = Settings()) -> DataFrame:
    """The rows that `score` gives with the model that `fit` gives, for which each text is turned into numbers once."""
    rows = _rows(df, id_col, text_col, learn_from)
    model, class_counts = _counted(rows.where("use"), settings)
    encoded = _encoded(rows, model)
    return _scored(encoded, replace(model, network=train(encoded.where("use").select("numbers"), model.words, class_counts)))


def _counted(rows: DataFrame, settings: Settings) -> tuple[Model, np.ndarray]:
    """All of a model but its network, and the counts of the classes."""
    counts = materialize(count_tokens(rows.select("text")), "token-counts")
    total, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    common = _most_common(counts, settings.common)

    words = word_maps(counts, settings)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, tallies = np.zeros(words.classes), np.zeros(words.classes)
        for b in batches:
            own = pc.fill_null(pc.index_in(b.column(0), pa.array(list(words.singles), pa.binary())), -1).to_numpy()  # in the order of their classes
            classes = np.where(own < 0, words.classes_of(b.column(0)), own)
            c = b.column(1).to_numpy(zero_copy_only=False)
            sums += np.bincount(classes, c + 0.5, words.classes)
            tallies += np.bincount(classes, c, words.classes)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(words.classes)), pa.array(sums), pa.array(tallies)], ["k", "s", "c"])

    sums, class_counts = np.zeros(words.classes), np.zeros(words.classes)
    for r in counts.mapInArrow(kernel, "k bigint, s double, c double").groupBy("k").agg(F.sum("s").alias("s"), F.sum("c").alias("c")).collect():  # a row for each class
        sums[r.k], class_counts[r.k] = r.s, r.c
    own = np.zeros(words.classes, bool)
    own[list(words.singles.values())] = True
    alone = rows.sparkSession.createDataFrame([(bytearray(w),) for w in words.singles], "word binary")  # as many as the settings say
    single = {bytes(r.word): r.c for r in counts.join(F.broadcast(alone), "word").collect()}
    sums[own] = [single.get(w, 0) + 0.5 for w in words.singles]
    return Model(words, None, counts, total, distinct, common, np.log10(np.where(own, sums, sums + 0.5))), class_counts


@dataclass
class Encoded:
    """Texts as numbers, one after the other, and what is known of each."""

    numbers: np.ndarray  # input << 12 | class
    ends: np.ndarray  # of the texts
    known: np.ndarray  # common tokens
    logs: np.ndarray  # their sums of log10 (c + 1/2)
    others: pa.ListArray  # other words and how often they occur

    @property
    def lists(self) -> list[np.ndarray]:
        return np.split(self.numbers, self.ends)[:-1]


class _Scorer:
    """Works on one executor: tokens to numbers, and numbers to probabilities."""

    def __init__(self, words: Words, network: Network | None, common: dict[bytes, int], class_log10: np.ndarray):
        self.words, self.network, self.class_log10 = words, network, class_log10
        listed, number = list(dict.fromkeys([*common, *words.inputs, *words.singles])), words.numbering()
        self.listed = pa.array(listed, pa.binary())
        self.numbers = np.array([*map(number, listed), 0], np.int32)
        self.log10 = np.log10(np.array([*common.values(), *[0.5] * (len(listed) + 1 - len(common))]) + 0.5)
        self.log10[len(common) :] = 0.0  # the count of any other word is joined later
        self.common = len(common)

    def encode(self, texts: pa.Array) -> Encoded:
        words, ends = split(texts)
        place = pc.fill_null(pc.index_in(words, self.listed), len(self.listed)).to_numpy()
        numbers = self.numbers.take(place)
        strange = np.flatnonzero(place == len(self.listed))
        classes = self.words.classes_of(words.take(pa.array(strange)))
        numbers[strange] = 1 + self.words.settings.inputs + classes << 12 | classes

        begins, logs = np.r_[0, ends][:-1], self.log10.take(place)
        sums = np.array([logs[a:b].sum() for a, b in zip(begins.tolist(), ends.tolist(), strict=True)], np.float64)
        other = np.flatnonzero(place >= self.common)
        met = words.take(pa.array(other)).dictionary_encode()
        text, n_met = np.searchsorted(ends, other, "right"), max(1, len(met.dictionary))
        keys, n = np.unique(text * n_met + met.indices.to_numpy(), return_counts=True)
        bounds = np.searchsorted(keys, n_met * np.arange(len(ends) + 1)).astype(np.int32)
        found = pa.StructArray.from_arrays([met.dictionary.take(pa.array(keys % n_met)), pa.array(n, pa.int64())], ["word", "n"])
        return Encoded(numbers, ends, ends - begins - np.bincount(text, minlength=len(ends)), sums, pa.ListArray.from_arrays(pa.array(bounds), found))

    def rest(self, lists: list[np.ndarray]) -> Iterator[float]:
        """For each text, as numbers: the part of its log10 probability that is not its words' log10 (c + 1/2)."""
        stretch = self.words.settings.stretch
        for lo, hi in _blocks([len(x) for x in lists], 1 << 16):
            ids, at = padded([x >> 12 for x in lists[lo:hi]], stretch)
            classes = np.concatenate(lists[lo:hi]) & 0xFFF
            logs = np.empty(len(at))
            for a in range(0, len(at), _PLACES):  # a very long text is worked off in stretches too
                b = min(a + _PLACES, len(at))
                first = at[a] - 1 - stretch
                h = self.network.contexts(ids[first : at[b - 1] + 1], at[a:b] - first, stretch)
                logs[a:b] = self.network.log10_classes(h, classes[a:b])
            logs -= self.class_log10.take(classes)
            to = 0
            for x in lists[lo:hi]:
                yield float(logs[to : to + len(x)].sum())
                to += len(x)

    def score(self, texts: list[str | None]) -> Iterator[tuple[int, int, float, float]]:
        """For each text: tokens, known common tokens, their sum of log10 (c + 1/2), the rest of its log10 probability."""
        e = self.encode(pa.array(texts, pa.string()))
        return zip(map(len, e.lists), e.known.tolist(), e.logs.tolist(), self.rest(e.lists), strict=True)


_SCORERS: dict[str, _Scorer] = {}


def _scorer(name: str, make) -> _Scorer:
    """The scorer of a model, made once in a process for all tasks that use it."""
    if name not in _SCORERS:
        _SCORERS.clear()
        _SCORERS[name] = make()
    return _SCORERS[name]


def _blocks(sizes: list[int], most: int) -> Iterator[tuple[int, int]]:
    lo = held = 0
    for i, n in enumerate(sizes):
        if held and held + n > most:
            yield lo, i
            lo, held = i, 0
        held += n
    if lo < len(sizes):
        yield lo, len(sizes)


def _encoded(rows: DataFrame, model: Model) -> DataFrame:
    """Rows (key, id, use, numbers, n, logs, others): each text as `_Scorer.encode` gives it, written once for training and scores."""
    kind = rows.schema["id"].dataType.simpleString()
    sent = rows.sparkSession.sparkContext.broadcast((model.words, None, model.common, model.class_log10))  # sizes fixed by the settings
    name = uuid.uuid4().hex

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = _scorer(name, lambda: _Scorer(*sent.value))
        key = TaskContext.get().partitionId() << 33
        for whole in batches:
            at = 0
            for texts in parts(whole.column(1)):
                b, e = whole.slice(at, len(texts)), scorer.encode(texts)
                at += len(texts)
                keys = pa.array(np.arange(key, key + len(texts)))
                key += len(texts)
                numbers = pa.Array.from_buffers(pa.binary(), len(texts), [None, pa.py_buffer(np.r_[0, 4 * e.ends].astype(np.int32)), pa.py_buffer(e.numbers)])
                yield pa.RecordBatch.from_arrays([keys, b.column(0), b.column(2), numbers, pa.array(e.known, pa.int64()), pa.array(e.logs), e.others], ["key", "id", "use", "numbers", "n", "logs", "others"])

    return materialize(rows.mapInArrow(kernel, f"key bigint, id {kind}, use boolean, numbers binary, n bigint, logs double, others array<struct<word: binary, n: bigint>>"), "numbers")


def score(df: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, n_tokens, n_known, train_tokens, base_score, score): one for each row of df."""
    return _scored(_encoded(_rows(df, id_col, text_col), model), model)


#: Words of a partition, on average, up to which a task keeps their counts in a map; more are sorted, and may lie on disk.
_MAPPED = 1 << 18


def _scored(encoded: DataFrame, model: Model) -> DataFrame:
    kind = encoded.schema["id"].dataType.simpleString()
    sent = encoded.sparkSession.sparkContext.broadcast((model.words, model.network, {}, model.class_log10))  # sizes fixed by the settings
    name = uuid.uuid4().hex

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = _scorer(name, lambda: _Scorer(*sent.value))
        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                b = whole.slice(lo, 256)
                lists = [np.frombuffer(x.as_buffer(), np.int32) for x in b.column(2)]
                yield pa.RecordBatch.from_arrays(
                    [b.column(0), b.column(1), b.column(3), b.column(4), pa.array([len(x) for x in lists], pa.int64()), pa.array(list(scorer.rest(lists)), pa.float64())],
                    ["key", "id", "n", "logs", "n_tokens", "rest"],
                )

    made = encoded.select("key", "id", "numbers", "n", "logs").mapInArrow(kernel, f"key bigint, id {kind}, n bigint, logs double, n_tokens bigint, rest double")
    made = materialize(made, "scored")
    few = model.distinct <= _MAPPED * int(encoded.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    counts = model.counts.hint("shuffle_hash" if few else "merge")
    others = encoded.select("key", F.explode("others").alias("other")).select("key", "other.word", "other.n").join(counts, "word", "left")
    log10 = F.log10(F.coalesce("c", F.lit(0)) + 0.5)
    others = others.groupBy("key").agg(F.sum(F.col("n") * log10).alias("more"), F.sum(F.when(F.col("c") > 0, F.col("n")).otherwise(0)).alias("more_known"))
    joined = made.join(others, "key", "left")
    logs = F.col("logs") + F.coalesce("more", F.lit(0.0))
    each = F.log10(F.lit(model.total + 0.5 * (model.distinct + 1)))
    return joined.select(
        "id", "n_tokens", (F.col("n") + F.coalesce("more_known", F.lit(0))).alias("n_known"), F.lit(model.total).cast("bigint").alias("train_tokens"), (logs - F.col("n_tokens") * each).alias("base_score"), (logs + F.col("rest")).alias("score")
    )
