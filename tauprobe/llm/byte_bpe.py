"""Byte-level BPE encoding and decoding with the tokenizers library over Arrow batches.

`encode` adds token ids (and, on request, character offsets) to a frame of texts, `decode` turns ids back into bytes
and text. The vocabulary is a rank file (base64 token, rank); merges are derived from the ranks, so that the library's
merge order is the order of the ranks. Every match of the split pattern is encoded on its own.

Defined results: a null text counts as empty (no ids); empty and very long texts are whole (long ones are worked off in
segments cut where the pattern always has a boundary); repeated rows give repeated results; an empty table gives an empty
table; only the named id and text columns are read, so other columns can have any name.
"""

from __future__ import annotations

import base64
import codecs
import hashlib
import itertools
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tauprobe.llm.arrow_kernels import Memory, run, segments

@lru_cache(1)
def byte_chars() -> tuple[str, ...]:
    """The printable character that stands for each byte: itself where it is visible, else one from 256 on."""
    seen = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    rest = (b for b in range(256) if b not in set(seen))
    table = {b: chr(b) for b in seen} | {b: chr(256 + i) for i, b in enumerate(rest)}
    return tuple(table[b] for b in range(256))


def to_chars(token: bytes) -> str:
    chars = byte_chars()
    return "".join(chars[b] for b in token)


def from_chars(token: str) -> bytes:
    back = {c: b for b, c in enumerate(byte_chars())}
    return bytes(back[c] for c in token)


@lru_cache(4)
def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f) if token}


def merges_of(ranks: dict[bytes, int]) -> list[tuple[bytes, bytes]]:
    """The merge that makes each token of several bytes: the two parts left when only lower ranks are joined."""
    merges = []
    for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
        parts = [token[i : i + 1] for i in range(len(token))]
        while len(parts) > 2:
            at = min(range(len(parts) - 1), key=lambda i: ranks.get(parts[i] + parts[i + 1], rank))
            if ranks.get(parts[at] + parts[at + 1], rank) >= rank:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        if len(parts) == 2:
            merges.append((parts[0], parts[1]))
    return merges


@lru_cache(4)
def tokenizer(path: str, pattern: str):
    """The tokenizers object for a rank file and a split pattern."""
    from tokenizers import Regex, Tokenizer, models, pre_tokenizers

    ranks = read_ranks(path)
    merges = [(to_chars(a), to_chars(b)) for a, b in merges_of(ranks)]
    made = Tokenizer(models.BPE({to_chars(t): r for t, r in ranks.items()}, merges))
    made.pre_tokenizer = pre_tokenizers.Sequence(
        [pre_tokenizers.Split(Regex(pattern), "removed", invert=True), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)]
    )
    return made


class Encoder:
    """Encodes texts; what it finds for a pre-token is remembered as little-endian 32-bit ids."""

    def __init__(self, path: str, pattern: str):
        import regex

        self.path, self.pattern = path, pattern
        self.split = regex.compile(pattern).findall
        self.model = tokenizer(path, pattern).model
        self.memory = Memory(self._learn, 1 << 16)

    def _learn(self, words: list[str]) -> list[bytes]:
        chars, tokenize = byte_chars(), self.model.tokenize
        return [np.array([t.id for t in tokenize("".join([chars[b] for b in w.encode()]))], "<u4").tobytes() for w in words]

    def ids(self, text: str) -> bytes:
        out = []
        for part in segments(text):
            words = self.split(part)
            out += map(self.memory.fill(words).__getitem__, words)
        return b"".join(out)

    def with_offsets(self, text: str) -> tuple[list[int], list[tuple[int, int]]]:
        """Ids and the character span of each; tokens that split a character have that character's span."""
        e = tokenizer(self.path, self.pattern).encode(text, add_special_tokens=False)
        return e.ids, e.offsets


@lru_cache(4)
def encoder(path: str, pattern: str) -> Encoder:
    return Encoder(path, pattern)


@lru_cache(4)
def byte_table(path: str) -> list[bytes]:
    ranks = read_ranks(path)
    table = [b""] * (max(ranks.values(), default=-1) + 1)
    for token, rank in ranks.items():
        table[rank] = token
    return table


def decode_ids(ids: list[int], path: str) -> bytes:
    return b"".join(map(byte_table(path).__getitem__, ids))


class StreamDecoder:
    """Decodes ids as they come; bytes of a character that is split over tokens wait for the rest of it."""

    def __init__(self, path: str):
        self.table = byte_table(path)
        self.held = codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, ids: list[int]) -> str:
        return self.held.decode(b"".join(map(self.table.__getitem__, ids)))

    def finish(self) -> str:
        return self.held.decode(b"", True)


def _lists(column) -> tuple[np.ndarray, np.ndarray]:
    """Bounds and values of a list column without nulls, honouring a slice's offset."""
    bounds = column.offsets.to_numpy()
    return bounds - bounds[0], column.flatten().to_numpy(zero_copy_only=False)


def encode_step(path: str, pattern: str, offsets: bool = False):
    """Batch function: (id, text) to (id, ids[, starts, ends])."""

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        enc = encoder(path, pattern)
        texts = [t or "" for t in batch.column(1).to_pylist()]
        if offsets:
            pairs = [enc.with_offsets(t) for t in texts]
            return pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([i for i, _ in pairs], pa.list_(pa.int32()))]
                + [pa.array([[o[k] for o in at] for _, at in pairs], pa.list_(pa.int32())) for k in (0, 1)],
                ["id", "ids", "starts", "ends"],
            )
        packed = [enc.ids(t) for t in texts]
        bounds = np.cumsum([0, *(len(p) // 4 for p in packed)]).astype("i4")
        values = pa.array(np.frombuffer(b"".join(packed), "<i4"))
        return pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(bounds), values)], ["id", "ids"])

    return step


def decode_step(path: str):
    """Batch function: adds the decoded bytes to (id, ids)."""

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        bounds, values = _lists(batch.column(1))
        flat = values.tolist()
        raw = [decode_ids(flat[a:b], path) for a, b in itertools.pairwise(bounds.tolist())]
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(raw, pa.binary())], ["id", "ids", "raw"])

    return step


def _text_step(batch: pa.RecordBatch) -> pa.RecordBatch:
    texts = pa.array([raw.decode("utf-8", "replace") for raw in batch.column(2).to_pylist()], pa.string())
    return pa.RecordBatch.from_arrays([*batch.columns, texts], ["id", "ids", "raw", "text"])


def _digest_step(batch: pa.RecordBatch) -> pa.RecordBatch:
    """(id, ids, raw) to counts and digests."""
    bounds, values = _lists(batch.column(1))
    words = list(map(str, values.tolist()))
    spans = list(itertools.pairwise(bounds.tolist()))
    return pa.RecordBatch.from_arrays(
        [
            batch.column(0),
            pa.array([b - a for a, b in spans], pa.int64()),
            pa.array([hashlib.sha256(" ".join(words[a:b]).encode()).hexdigest() for a, b in spans], pa.string()),
            pa.array([hashlib.sha256(raw).hexdigest() for raw in batch.column(2).to_pylist()], pa.string()),
        ],
        ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
    )


def encode(df: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", offsets: bool = False) -> DataFrame:
    """Frame of (id, ids[, starts, ends]): one row for each row of df."""
    picked = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    kind = picked.schema["id"].dataType.simpleString()
    return run(picked, [encode_step(path, pattern, offsets)], f"id {kind}, ids array<int>" + ", starts array<int>, ends array<int>" * offsets)


def decode(df: DataFrame, path: str, id_col: str = "id", ids_col: str = "ids") -> DataFrame:
    """Frame of (id, ids, raw, text): the bytes of the ids, and their text with replacement characters for broken UTF-8."""
    picked = df.select(F.col(id_col).alias("id"), F.coalesce(F.col(ids_col), F.array().cast("array<int>")).alias("ids"))
    kind = picked.schema["id"].dataType.simpleString()
    return run(picked, [decode_step(path), _text_step], f"id {kind}, ids array<int>, raw binary, text string")


def round_trip(df: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts and digests of encoding and then decoding each text, in one pass over the batches."""
    picked = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    kind = picked.schema["id"].dataType.simpleString()
    return run(picked, [encode_step(path, pattern), decode_step(path), _digest_step], f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
