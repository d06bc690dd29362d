"""Byte-level BPE, token files and chat formatting against the libraries, brute force and exact round trips."""

import base64
import hashlib
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from tauprobe.llm import byte_bpe, chat, queries, token_files
from tauprobe.llm.arrow_kernels import segments
from tauprobe.session import scratch

SF = "/root/testdata/sf0.001"
RANKS, WORDS = P.path("byte_bpe_50k.tiktoken"), P.path("word_bpe_49k.json")
ODD = [None, "", " ", "a", "\n\n  x\t", "It's 2024\u2029 \x1c don't<|endoftext|>", "\U0001f600\u00e9e\u0301 " * 7, "word " * 300_000, "z" * 70_000, "\u1680\x85 a\u00a0b"]


@pytest.fixture(scope="module")
def tik():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=80))
def test_bpe_equals_tiktoken(text):
    ranks = byte_bpe.read_ranks(RANKS)
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    ids = np.frombuffer(byte_bpe.encoder(RANKS, P.PATTERN).ids(text), "<u4").tolist()
    assert ids == enc.encode_ordinary(text)
    assert byte_bpe.decode_ids(ids, RANKS) == text.encode()
    stream = byte_bpe.StreamDecoder(RANKS)
    assert "".join(stream.feed([i]) for i in ids) + stream.finish() == text


def test_bpe_query_and_odd_rows(spark, tik):
    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas()
    got = queries.op6_byte_bpe(spark, SF).toPandas().set_index("doc_id")
    assert len(got) == len(docs)
    for d, text in zip(docs.doc_id, docs.text, strict=True):
        ids = tik.encode_ordinary(text)
        want = len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(text.encode()).hexdigest()
        assert tuple(got.loc[d]) == want
    odd = spark.createDataFrame([(i, t, 1, "x") for i, t in enumerate(ODD)] + [(3, "a", 1, "x"), (None, "b", 1, "x")], "doc_id bigint, text string, n_tokens int, ids string")
    enc = byte_bpe.encode(odd, RANKS, P.PATTERN)
    for r in enc.collect():
        if r.id is not None:
            assert r.ids == tik.encode_ordinary(ODD[r.id] or "")
    assert sorted(r.text for r in byte_bpe.decode(enc, RANKS).collect()) == sorted([t or "" for t in ODD] + ["a", "b"])
    assert byte_bpe.round_trip(odd.limit(0), RANKS, P.PATTERN).count() == 0
    spans = byte_bpe.encode(odd.where("doc_id = 5"), RANKS, P.PATTERN, offsets=True).first()
    assert spans.starts[0] == 0 and spans.ends[-1] == len(ODD[5])


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=80))
def test_words_apart_equal_whole_text(text):
    assert token_files.word_encoder(WORDS).check(text)


WHITE = [c for c in map(chr, range(0x3001)) if c.isspace()]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.sampled_from([*WHITE, "a", "\u0301", "\u00e9,", "'s"]), max_size=12), st.integers(0, 8))
def test_cuts_of_long_texts_change_nothing(tail, back):
    """Runs of any white space around the place of a cut, against the libraries."""
    text = ("word " * 3000)[: 9000 - back] + "".join(tail) + " end\u00a0 \n x" * 40
    ranks = byte_bpe.read_ranks(RANKS)
    want = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary(text)
    parts = list(segments(text, 9000 - 4))
    enc = byte_bpe.encoder(RANKS, P.PATTERN)
    assert len(parts) > 1 and "".join(parts) == text
    assert [i for p in parts for i in np.frombuffer(enc.ids(p), "<u4").tolist()] == want
    words = token_files.word_encoder(WORDS)
    assert b"".join(words.ids(p) for p in parts) == np.array(words.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


def test_plain_words_are_bounded_and_exact():
    text = "It's <|ENDOFTEXT|> \u00c9t\u00e9s, \u00d710\u00b2\u00bd x_1 68.92.44.249 don't'\u00b5 " * 3 + " ".join(f"w{i}\u00e9,{i}" for i in range(300))
    enc = token_files.WordEncoder(WORDS)
    enc.plain.size = 50
    assert enc._split(text) and enc.check(text) and len(enc.plain) <= 50 >= len(enc.plain.past)
    assert enc.check(text + "<|endoftext|>") and enc.check(text + " \u0130\u212a")


def test_token_files(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas().sort_values("doc_id")
    got = queries.op5_token_files(spark, SF).toPandas().sort_values("doc_id")
    tok, start = Tokenizer.from_file(WORDS), 0
    assert list(got.doc_id) == list(docs.doc_id)
    for row, text in zip(got.itertuples(), docs.text, strict=True):
        ids = np.array([*tok.encode(text, add_special_tokens=False).ids, 2], "<u4")
        assert (row.start, row.n_tokens, row.ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


@pytest.mark.parametrize("compress", [True, False])
def test_token_files_odd_rows(spark, compress):
    rows = [(i, t) for i, t in enumerate(ODD)] + [(3, "a"), (None, "b")]
    clashing = spark.createDataFrame([(*r, "x", 1, 2.0) for r in rows], "doc_id bigint, text string, id string, shard int, tokens double")
    shards = token_files.write(clashing, scratch(spark, "t"), WORDS, 2, compress=compress)
    tok = Tokenizer.from_file(WORDS)
    got = token_files.read(spark, shards).orderBy("start").collect()
    assert [r.id for r in got] == sorted((d for d, _ in rows), key=lambda d: (d is not None, d))
    assert sorted(map(tuple, (r.ids for r in got))) == sorted(tuple(tok.encode(t or "", add_special_tokens=False).ids + [2]) for _, t in rows)
    shard = next(p[0] for p in shards.parts if p[1])
    index = token_files.read_index(shards.folder, shard)
    assert token_files.read_one(shards.folder, shard, index[-1])[-1] == 2
    empty = token_files.write(spark.createDataFrame([], "doc_id bigint, text string"), scratch(spark, "t"), WORDS, 2)
    assert token_files.read(spark, empty).count() == 0


def test_broken_records_raise():
    data = bytearray(token_files.frame(token_files.pack_ids(np.arange(9, dtype="<u4").tobytes(), False)))
    assert token_files.unpack_ids(token_files.unframe(bytes(data), 0)[0]).tolist() == list(range(9))
    for at in (0, 9, 15, len(data) - 1):
        data[at] ^= 1
        with pytest.raises(ValueError):
            token_files.unframe(bytes(data), 0)
        data[at] ^= 1


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "a:b", "", "\\"]) | st.text("#: \\</turn>\nx", max_size=12), st.text("#: \\</turn>\nx", max_size=30)), max_size=5))
def test_template_is_reversible(turns):
    t = chat.Template()
    parts = [p for role, text in turns for p in t.turn(role, text)]
    assert t.parse("".join(s for s, _ in parts)) == turns
    assert [t.unescaped(s) for s, loss in parts if loss] == [text for role, text in turns if role == "assistant"]


def test_chat_odd_rows(spark):
    rows = [(1, 0, "user", None, 7), (1, 1, "assistant", "", 7), (2, 1, "assistant", "b", 7), (2, 0, None, "a", 7), (3, 0, "user", "q", 7), (3, 0, "user", "q", 7), (None, 0, "user", "n", 7)]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string, valid int")
    got = {r.conv_id: r for r in chat.digests(df).collect()}
    assert {c: (r.n_turns, r.valid) for c, r in got.items()} == {1: (2, True), 2: (2, False), 3: (2, False), None: (1, False)}
    assert got[2].turns_sha256 == hashlib.sha256(b"\na\nassistant\nb\n").hexdigest()
    assert got[1].loss_chars == 0 and got[2].loss_sha256 == hashlib.sha256(b"b").hexdigest()
    assert chat.digests(df.limit(0)).count() == 0
    said = chat.segments_of(df).where("loss").orderBy("conv_id", "turn_no").collect()
    assert [(r.conv_id, r.text) for r in said] == [(1, ""), (2, "b")]


def test_chat_long_turns_and_ties(spark):
    """A turn of millions of characters, a conversation of thousands of turns, and turns that tie in everything."""
    long = "\\: </turn> ### \u00e9" * 150_000
    rows = [(1, 0, "user", long, "x"), (1, 1, "assistant", long, "x")]
    rows += [(2, i, "user" if i % 2 == 0 else "assistant", f"t{i}", "x") for i in range(6000)]
    rows += [(3, 0, "user", "same", "x"), (3, 0, "user", "same", "x"), (3, 0, "assistant", "b", "x"), (3, 0, "assistant", "a", "x")]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string, part string").repartition(3)
    got = {r.conv_id: r for r in chat.digests(df).collect()}
    assert got[1].loss_chars == len(long) and got[1].valid and got[1].loss_sha256 == hashlib.sha256(long.encode()).hexdigest()
    assert got[2].n_turns == 6000 and got[2].valid and got[2].loss_chars == sum(len(f"t{i}") for i in range(1, 6000, 2))
    assert got[3].turns_sha256 == hashlib.sha256(b"assistant\na\nassistant\nb\nuser\nsame\nuser\nsame\n").hexdigest() and not got[3].valid
    parts = chat.segments_of(df.where("conv_id = 1")).orderBy("turn_no", "part").collect()
    assert [p.loss for p in parts] == [False, False, False, False, True, False]
    assert chat.Template().parse("".join(p.text for p in parts)) == [("user", long), ("assistant", long)]
