import io
import random
import zlib

import numpy as np
import pyarrow as pa
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import types as T
from tokenizers import Tokenizer

from wsig.llm import token_file as K

PATH = public_tokenizers.path("byte_bpe_50k.json")
SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("start", T.LongType()), T.StructField("path", T.StringType())])


@settings(max_examples=200, deadline=None)
@given(st.lists(st.one_of(st.integers(0, 50), st.integers(0, 60000), st.integers(0, 2**32 - 1)), min_size=1, max_size=700))
def test_block_round_trip(ids):
    a = np.array(ids, np.uint32)
    assert (K.decode_block(np.frombuffer(K.encode_block(a), np.uint8)) == a).all()


def test_outliers_are_exceptions():
    a = np.full(4096, 1000, np.uint32)
    a[::64] = 2**31
    a[1::2] += 7
    block = K.encode_block(a)
    assert np.frombuffer(block[:12], K._HEAD)[0]["exceptions"] == 64 and len(block) < 4096 * 3 / 8 + 64 * 6 + 13
    assert (K.decode_block(np.frombuffer(block, np.uint8)) == a).all()


def test_shard_random_access():
    rng = np.random.default_rng(3)
    docs = [rng.integers(0, 50257, n).astype(np.uint32) for n in (1, 5000, 0, 3, 12000, 4096, 1)]
    out = io.BytesIO()
    w = K.Writer(out)
    for part in (docs[:3], docs[3:]):
        w.add(np.concatenate(part), np.array([len(d) for d in part]), pa.array([None, *range(-1, len(part) - 2)], pa.int64()))
    w.close()
    r = K.Reader(pa.BufferReader(out.getvalue()))
    assert all((r.document(i) == d).all() for i, d in enumerate(docs))
    assert r.doc_ids.to_pylist() == [None, -1, 0, None, -1, 0, 1]
    again = [(f, [*n], ids) for f, n, ids in r.documents(step=1)]
    assert np.concatenate([x for _, _, x in again]).tolist() == np.concatenate(docs).tolist()


def texts():
    random.seed(4)
    pieces = ["Hello", "it's", "naïve", "日本", "<|endoftext|>", "a,b", "\n", "\t", " ", "  ", " ", "x\ny", "'s", "12345", " ", "é!", "\x1c", "\x85", "\u2003", "“q”", "\u00a0", "Ġ", "Ċx"]
    return [" ".join(random.choices(pieces, k=random.randrange(9))) for _ in range(300)] + ["", " a", "a ", " ", "a\n b", "don't 've"]


def test_chunks_encode_like_the_whole_text():
    t = Tokenizer.from_file(PATH)
    want = [e.ids for e in t.encode_batch(texts(), add_special_tokens=False)]
    for batch in (texts(), [x for x in texts() if x.strip() == x and "\t" not in x], [], ["", None]):
        ids, lengths = K.Encoder.of(PATH).encode(pa.array(batch, pa.string()), 2)
        got = [x.tolist() for x in np.split(ids, np.cumsum(lengths))[:-1]]
        assert got == [t.encode(x or "", add_special_tokens=False).ids + [2] for x in batch]
    assert len(want) == len(texts())


def test_special_tokens_as_the_library_does():
    ids, lengths = K.Encoder.of(PATH).encode(pa.array(["hello <|endoftext|> x", "a<|endoftext|>", "<|endoftext", "|>"]), 2)
    t = Tokenizer.from_file(PATH)
    assert lengths.tolist() == [len(t.encode(x, add_special_tokens=False).ids) + 1 for x in ("hello <|endoftext|> x", "a<|endoftext|>", "<|endoftext", "|>")] and lengths[0] == 5


def test_files_against_direct_encoding(spark):
    rows = [(i * 3, t, 7, "clash") for i, t in enumerate(texts())] + [(None, "last", 0, None), (4, None, 0, None), (5, "word " * 60000, 0, None), (3, "again", 0, None)]
    t = Tokenizer.from_file(PATH)
    got = K.token_files(spark.createDataFrame(rows, SCHEMA).repartition(5), PATH).collect()
    assert len(got) == len(rows)
    want = {}
    for i, text, _, _ in rows:
        ids = t.encode(text or "", add_special_tokens=False).ids + [2]
        want.setdefault(i, []).append((len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
    start = 0
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == start and (r.n_tokens, r.ids_crc32) in want[r.doc_id]
        want[r.doc_id].remove((r.n_tokens, r.ids_crc32))
        start += r.n_tokens
    order = [r.doc_id for r in sorted(got, key=lambda r: r.start)]
    assert order[-1] is None and order[:-1] == sorted(order[:-1])
    assert K.token_files(spark.createDataFrame([], SCHEMA), PATH).count() == 0
