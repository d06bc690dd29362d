"""Token ids in length-delimited binary record files with an offset index.

File format, all numbers little-endian. A shard `shard-NNNNN.rec` starts with the eight bytes `TPREC001`; records follow.
A record is a frame: payload length (u64), masked checksum of those eight bytes (u32), payload, masked checksum of the
payload (u32). A checksum is CRC-32 rotated right by 15 bits plus 0xA282EAD8, so that a checksum stored inside checked
data does not spoil the outer one. A payload is one byte for the id width (2 or 4), one byte for the codec (0 plain,
1 zstd), then the ids. Beside each shard lies its index `shard-NNNNN.idx`: after `TPIDX001`, 32 bytes for each record:
document id (i64), 1 if that id is null else 0 (u32), token count (u32), byte offset of the frame (u64), ids before it in
the shard (u64). With it a reader gets at any record without reading the others, e.g. in shuffled order.

`write` tokenizes texts and writes the shards in ascending order of the id (nulls first, ties by text), one shard for each
range partition; `read` turns shards back into rows. Defined results: a null text counts as empty and yields the end id
alone; empty and very long texts are whole; repeated rows are repeated records; an empty table gives no records; only the
named id and text columns are read. A lost or repeated task rewrites its shard under a name of its own and then renames it.
"""

from __future__ import annotations

import json
import re
import struct
import uuid
import zlib
from array import array
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tauprobe.llm.arrow_kernels import SLICE_ROWS, Memory, segments
from tauprobe.llm.byte_bpe import byte_chars

MAGIC, INDEX_MAGIC = b"TPREC001", b"TPIDX001"
ENTRY = struct.Struct("<qIIQQ")
#: Fixed value: the split pattern of the tokenizer files that have the shorter way.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: The letters and the other numerals up to U+00FF, in lower case; and the same pattern over them.
_LETTERS, _NUMERALS = "a-zªµºß-öø-ÿ", "0-9²³¹¼½¾"
_PLAIN_PARTS = re.compile(rf"[{_LETTERS}]+|'(?:s|t|re|ve|m|ll|d)|[{_NUMERALS}]|[^\s{_LETTERS}{_NUMERALS}]+")
_PLAIN = re.compile("[!-~\u00a1-\u00ff \t\n\r]*+")
#: Fixed value of the mask.
MASK_DELTA = 0xA282EAD8


def masked(data: bytes) -> int:
    crc = zlib.crc32(data)
    return ((crc >> 15 | crc << 17) + MASK_DELTA) & 0xFFFFFFFF


def frame(payload: bytes) -> bytes:
    head = struct.pack("<Q", len(payload))
    return b"".join((head, struct.pack("<I", masked(head)), payload, struct.pack("<I", masked(payload))))


def unframe(data: bytes, at: int) -> tuple[bytes, int]:
    """The payload of the frame at this place, and the place after it; broken frames raise."""
    head = data[at : at + 8]
    if len(head) < 8 or struct.unpack_from("<I", data, at + 8)[0] != masked(head):
        raise ValueError(f"broken length at byte {at}")
    end = at + 12 + struct.unpack("<Q", head)[0]
    payload = data[at + 12 : end]
    if len(data) < end + 4 or struct.unpack_from("<I", data, end)[0] != masked(payload):
        raise ValueError(f"broken record at byte {at}")
    return payload, end + 4


def entry(key: int | None, count: int, at: int, before: int) -> bytes:
    """An index entry."""
    return ENTRY.pack(key or 0, key is None, count, at, before)


def head_length(head: bytes) -> int:
    """Bytes that follow the twelve of a frame's head."""
    return struct.unpack_from("<Q", head)[0] + 4


@lru_cache(1)
def _zstd():
    """One compressor and one decompressor of this process."""
    import zstandard

    return zstandard.ZstdCompressor(level=1), zstandard.ZstdDecompressor()


def pack_ids(ids: bytes, compress: bool) -> bytes:
    """Payload of ids given as unsigned 32-bit values."""
    values = np.frombuffer(ids, "<u4")
    narrow = not len(values) or values.max() < 1 << 16
    body = values.astype("<u2").tobytes() if narrow else ids
    if compress:
        body = _zstd()[0].compress(body)
    return bytes((2 if narrow else 4, int(compress))) + body


def unpack_ids(payload: bytes) -> np.ndarray:
    body = _zstd()[1].decompress(payload[2:]) if payload[1] else payload[2:]
    return np.frombuffer(body, "<u2" if payload[0] == 2 else "<u4").astype("<u4")


class _PlainWords(dict):
    """Ids of plain words in lower case, and of their parts, as they are asked for; two generations, so the size is bounded.

    A word that spells an added token only in lower case is not one, so the model gets the parts of every word.
    """

    def __init__(self, tokenize, size: int = 1 << 18):
        super().__init__()
        self.tokenize, self.size, self.chars = tokenize, size, dict(enumerate(byte_chars()))
        self.past: dict[str, bytes] = {}

    def __missing__(self, word: str) -> bytes:
        if (found := self.past.get(word)) is None:
            if not word.isalpha() and len(parts := _PLAIN_PARTS.findall(word)) > 1:
                found = self.ids(parts)
            else:
                spelt = word if word.isascii() else word.encode().decode("latin-1").translate(self.chars)
                found = array("I", [t.id for t in self.tokenize(spelt)]).tobytes()
        if len(self) >= self.size:
            self.past = dict(self)
            self.clear()
        self[word] = found
        return found

    def ids(self, words: list[str]) -> bytes:
        return b"".join(map(self.__getitem__, words))


class WordEncoder:
    """Encodes texts with a tokenizer file. Words between white space are encoded apart, and remembered.

    The split pattern of the tokenizer must never match across white space, and its normalizer must work on characters;
    both hold for tokenizers that drop white space. Texts of characters up to U+00FF, which no normal form changes, are
    put in lower case and split at white space here, and the parts of new words go to the library's model; of other texts,
    each word does so or takes the library's whole way.
    `check` compares with the library on whole texts.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        plan = json.loads(self.whole.to_str())
        steps = [s["type"] for s in plan["normalizer"]["normalizers"]], [s["type"] for s in plan["pre_tokenizer"]["pretokenizers"]]
        self.short_way = steps == (["NFC", "Replace", "Lowercase"], ["Split", "ByteLevel"]) and plan["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"] == WORD_PATTERN
        self.added = tuple(t["content"] for t in plan["added_tokens"])
        self.plain = _PlainWords(self.whole.model.tokenize)
        self.words = Memory(self._learn)

    def _split(self, text: str) -> list[str] | None:
        """The words of a text of plain characters, in lower case."""
        return text.lower().split() if self.short_way and _PLAIN.fullmatch(text) and not any([a in text for a in self.added]) else None

    def _learn(self, words: list[str]) -> list[bytes]:
        split = [self._split(w) for w in words]
        return [
            array("I", self.whole.encode(w, add_special_tokens=False).ids).tobytes() if own is None else self.plain.ids(own)
            for w, own in zip(words, split, strict=True)
        ]

    def ids_of(self, texts: list[str]) -> list[bytes]:
        """32-bit ids of each text."""
        split = [self._split(t) for t in texts]
        out = [b"" if words is None else self.plain.ids(words) for words in split]
        for i, words in enumerate(split):
            if words is None:
                words = texts[i].replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")
                out[i] = b"".join(map(self.words.fill(words).__getitem__, words))
        return out

    def ids(self, text: str) -> bytes:
        return b"".join(b"".join(self.ids_of([part])) for part in segments(text))

    def many(self, texts: list[str]) -> list[bytes]:
        """As ids, for many texts; long ones are worked off alone and in segments."""
        short = [i for i, t in enumerate(texts) if len(t) < 1 << 18]
        found = dict(zip(short, self.ids_of([texts[i] for i in short]), strict=True))
        return [found[i] if i in found else self.ids(t) for i, t in enumerate(texts)]

    def check(self, text: str) -> bool:
        return self.ids(text) == np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


@lru_cache(2)
def word_encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


@dataclass(frozen=True)
class Shards:
    """What was written: the folder, and (shard number, records, tokens) of each shard in the order of the ids."""

    folder: str
    parts: tuple[tuple[int, int, int], ...]

    def starts(self) -> dict[int, int]:
        before, total = {}, 0
        for number, _, tokens in self.parts:
            before[number], total = total, total + tokens
        return before


def _filesystem(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder if "://" in folder else "file://" + folder.removeprefix("file:"))


def write(df: DataFrame, folder: str, tokenizer_path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", compress: bool = True) -> Shards:
    """Tokenizes every text, appends the end id and writes the shards; the driver gets one small row for each shard."""
    picked = df.select(F.col(id_col).cast("bigint").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    ordered = picked.repartitionByRange(F.col("id").asc_nulls_first()).sortWithinPartitions(F.col("id").asc_nulls_first(), "text")
    end = np.array([end_id], "<u4").tobytes()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = word_encoder(tokenizer_path)
        store, base = _filesystem(folder)
        number = TaskContext.get().partitionId()
        own = f"{base}/.{uuid.uuid4().hex}"
        store.create_dir(base, recursive=True)
        at, tokens, index, records = len(MAGIC), 0, [INDEX_MAGIC], 0
        with store.open_output_stream(f"{own}.rec") as out:
            out.write(MAGIC)
            for batch in batches:
                for lo in range(0, batch.num_rows, SLICE_ROWS):
                    few = batch.slice(lo, SLICE_ROWS)
                    frames = []
                    for key, ids in zip(few.column(0).to_pylist(), enc.many(few.column(1).to_pylist()), strict=True):
                        ids += end
                        made = frame(pack_ids(ids, compress))
                        index.append(entry(key, len(ids) // 4, at, tokens))
                        frames.append(made)
                        at, tokens, records = at + len(made), tokens + len(ids) // 4, records + 1
                    out.write(b"".join(frames))
        with store.open_output_stream(f"{own}.idx") as out:
            out.write(b"".join(index))
        for kind in ("rec", "idx"):
            store.move(f"{own}.{kind}", f"{base}/shard-{number:05d}.{kind}")
        yield pa.RecordBatch.from_pydict({"shard": [number], "records": [records], "tokens": [tokens]}, pa.schema([("shard", pa.int32()), ("records", pa.int64()), ("tokens", pa.int64())]))

    made = ordered.mapInArrow(kernel, "shard int, records bigint, tokens bigint").collect()  # one row for each shard
    return Shards(folder, tuple(sorted((r.shard, r.records, r.tokens) for r in made)))


def read_index(folder: str, shard: int) -> np.ndarray:
    store, base = _filesystem(folder)
    with store.open_input_stream(f"{base}/shard-{shard:05d}.idx") as f:
        data = f.read()
    if data[:8] != INDEX_MAGIC:
        raise ValueError("not an index")
    return np.frombuffer(data[8:], [("id", "<i8"), ("null", "<u4"), ("n", "<u4"), ("at", "<u8"), ("before", "<u8")])


def read_one(folder: str, shard: int, entry) -> np.ndarray:
    """The ids of one record, found through its index entry."""
    store, base = _filesystem(folder)
    with store.open_input_file(f"{base}/shard-{shard:05d}.rec") as f:
        f.seek(int(entry["at"]))
        head = f.read(12)
        rest = f.read(head_length(head))
    return unpack_ids(unframe(head + rest, 0)[0])


def read(spark: SparkSession, shards: Shards, ids: bool = True) -> DataFrame:
    """Rows (id, start, n_tokens, ids_crc32[, ids]) from the files; start counts the ids of all records before it."""
    folder, starts = shards.folder, shards.starts()
    numbers = [p[0] for p in shards.parts]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = _filesystem(folder)
        for place in (p for b in batches for p in b.column(0).to_pylist()):
            shard = numbers[place]
            index = read_index(folder, shard)
            with store.open_input_stream(f"{base}/shard-{shard:05d}.rec", buffer_size=1 << 20) as f:
                if f.read(8) != MAGIC:
                    raise ValueError("not a record file")
                for lo in range(0, len(index), SLICE_ROWS):
                    few = index[lo : lo + SLICE_ROWS]
                    got = []
                    for _ in few:
                        head = f.read(12)
                        got.append(unpack_ids(unframe(head + f.read(head_length(head)), 0)[0]))
                    columns = [
                        pa.array(few["id"].astype("i8"), pa.int64(), mask=few["null"] == 1),
                        pa.array(few["before"].astype("i8") + starts[shard]),
                        pa.array([len(x) for x in got], pa.int64()),
                        pa.array([zlib.crc32(x.tobytes()) for x in got], pa.int64()),
                    ]
                    if ids:
                        columns.append(pa.array([x.astype("i8") for x in got], pa.list_(pa.int64())))
                    yield pa.RecordBatch.from_arrays(columns, ["id", "start", "n_tokens", "ids_crc32", "ids"][: len(columns)])

    return spark.range(len(numbers), numPartitions=max(1, len(numbers))).mapInArrow(kernel, "id bigint, start bigint, n_tokens bigint, ids_crc32 bigint" + ", ids array<bigint>" * ids)
