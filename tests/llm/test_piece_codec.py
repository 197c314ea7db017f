import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import types as T
from sentencepiece import SentencePieceProcessor

from wsig.llm import piece_codec as P

PATH = public_tokenizers.path("piece_bpe_32k.model")
SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("pieces", T.StringType()), T.StructField("n_pieces", T.LongType())])
TEXTS = ["Hello world", "  two  spaces ", "tab\tnl\n x", "日本語 é ﬁ ①", "", " ", "a▁b ▁", "​zero", "é", "internationalisation of the thing", "x" * 200 + "the" * 90, "a" * 47, "a" * 48, "a" * 49, "\x00\x01 end  ", "🙂🙂 ok"]


def codec(alpha, cache={}):
    if alpha not in cache:
        cache[alpha] = P.Codec(PATH, alpha)
    return cache[alpha]


def ids(c, texts, docs=None, copies=None):
    raw = [t.encode() for t in texts]
    offsets = np.concatenate(([0], np.cumsum([len(x) for x in raw]))).astype(np.int64)
    docs = np.arange(len(texts)) if docs is None else np.array(docs)
    out, counts = c.encode(np.frombuffer(b"".join(raw), np.uint8), offsets, docs.astype(np.uint64), copies)
    return [x.tolist() for x in np.split(out, np.cumsum(counts)[:-1])] if texts else []


def naive(c, text, doc, alpha, seed=P.SEED):
    """The best pair that its hash allows, leftmost first, again and again over the whole text."""
    if not text:
        return []
    p = c.pieces
    symbols = [p.symbol(x) for x in " " + text]
    places = list(range(len(symbols)))
    key = int(P.text_key(seed, np.array([doc], np.uint64))[0])
    while True:
        best = None
        for i in range(len(symbols) - 1):
            piece = p.pairs.get(symbols[i] << P._SHIFT | symbols[i + 1])
            if piece is not None and (best is None or p.rank[piece] < best[0]) and P.one_hash(key, places[i], piece) >= P._limit(alpha):
                best = (p.rank[piece], i, piece)
        if best is None:
            break
        _, i, piece = best
        symbols[i : i + 2], places[i : i + 2] = [piece], [places[i]]
    out = []
    for s in symbols:
        out += [s] if s < p.n else p.byte_ids[list(p.strange[s - p.n])].tolist()
    return out


def back(c, encoded):
    counts = np.array([len(x) for x in encoded])
    data, lengths = c.decode(np.array([i for x in encoded for i in x], np.int64), counts)
    edges = np.concatenate(([0], np.cumsum(lengths)))
    return [data[a:b].tobytes().decode() for a, b in zip(edges, edges[1:])]


def test_without_dropout_as_the_library():
    sp = SentencePieceProcessor(model_file=PATH)
    texts = [t for t in TEXTS if P.MARK not in t]
    assert ids(codec(0.0), texts) == [sp.encode(t) for t in texts]


@settings(max_examples=120, deadline=None)
@given(st.lists(st.text(alphabet="abthe ing  é▁日\n🙂", max_size=60), max_size=8), st.sampled_from([0.0, 0.1, 0.4, 1.0]))
def test_as_the_naive_loop_and_back(texts, alpha):
    c = codec(alpha)
    got = ids(c, texts)
    assert got == [naive(c, t, i, alpha) for i, t in enumerate(texts)]
    assert back(c, got) == texts


def test_long_and_short_chunks_by_the_same_rule(monkeypatch):
    texts = ["x" * 90 + "the" * 40, "internationalisation of the thing " * 4, "a" * 47, "a" * 48, "a" * 49, "日本語" * 30, TEXTS[1], ""]
    for alpha in (0.0, 0.2):
        c = codec(alpha)
        want = [naive(c, t, i, alpha) for i, t in enumerate(texts)]
        for wide in (0, 3, 48, 1000):
            monkeypatch.setattr(P, "WIDE", wide)
            assert ids(c, texts) == want
        monkeypatch.setattr(P, "TOGETHER", 3)
        monkeypatch.setattr(P, "CELLS", 20)
        assert ids(c, texts) == want


def test_hash_in_python_as_in_numpy():
    rng = np.random.default_rng(2)
    key, place, piece = rng.integers(0, 2**63, 50, dtype=np.uint64) * np.uint64(2), rng.integers(0, 10**6, 50), rng.integers(0, 32000, 50)
    assert P.hashes(key, place, piece).tolist() == [P.one_hash(*map(int, x)) for x in zip(key, place, piece)]


def test_dropout_varies_by_document_place_copy_and_seed():
    text = " ".join(["internationalisation"] * 400)
    c = P.Codec(PATH, 0.2)
    a, b = ids(c, [text, text])
    other = ids(P.Codec(PATH, 0.2, seed=5), [text])[0]
    assert a != b and a != other and ids(c, [text, text])[0] == a
    one, two = ids(c, [text, text], [7, 7], np.array([0, 1], np.uint64))
    assert one != two and back(c, [one, two]) == [text, text]
    assert len(a) > len(ids(codec(0.0), [text])[0])
    assert len(ids(codec(1.0), ["the thing"])[0]) == 10
    words, now = set(), []
    for piece in a:  # a segmentation of its own at most occurrences
        if c.pieces.table[c.pieces.places[piece]] == 32 and now:
            words.add(tuple(now))
            now = []
        now.append(piece)
    assert len(words) > 20


def test_query_and_decode(spark):
    rows = [(i, t, "clash", 0) for i, t in enumerate(TEXTS)] + [(None, "no id", None, None), (50, None, None, None), (51, "w " * 50000, None, None), (1, TEXTS[1], None, None)]
    df = spark.createDataFrame(rows, SCHEMA).repartition(3)
    out = P.encode_pieces(df, PATH)
    got = out.collect()
    assert len(got) == len(rows) and all(r.lossless for r in got) and all(r.n_pieces == len(r.pieces) for r in got)
    texts = sorted(r.text for r in P.decode_pieces(out, PATH).collect())
    assert texts == sorted(t or "" for _, t, _, _ in rows)
    assert P.encode_pieces(df.limit(0), PATH).count() == 0
