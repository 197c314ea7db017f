import re

import numpy as np
import pyarrow as pa
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import types as T

from wsig.llm import quality_rules as Q
from wsig.llm.textscan import Scan

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("kept", T.StringType()), T.StructField("n_words", T.StringType())])


def brute(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    again = {i + k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(8)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(again)


@settings(max_examples=400, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="ab é \n\t\r\x0b|#\xa0🙂", max_size=80), st.text(alphabet="a ", max_size=60)), max_size=6))
def test_base_counts(texts):
    got = Q.base_rules(Scan(pa.array(texts, pa.string())))
    columns = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    assert list(zip(*[got[c].tolist() for c in columns])) == [brute(t) for t in texts]


def brute_kneser_ney(grams, counts):
    """Interpolated modified Kneser-Ney by dictionaries; grams are tuples of classes."""
    order = Q.ORDER

    def smooth(c):
        n = [max(1, sum(v == i for v in c.values())) for i in range(1, 5)]
        y = n[0] / (n[0] + 2 * n[1])
        d = [0.0] + [min(max(i + 1 - (i + 2) * y * n[i + 1] / n[i], 0.0), hi) for i, hi in zip(range(3), (0.95, 1.9, 2.85))]
        total, left = {}, {}
        for g, v in c.items():
            total[g[:-1]] = total.get(g[:-1], 0) + v
            left[g[:-1]] = left.get(g[:-1], 0) + d[min(v, 3)]
        return c, d, total, left

    levels = {order: smooth(dict(zip(grams, counts)))}
    for m in range(order - 1, 0, -1):
        c = {}
        for g in {g[order - m - 1 :] for g in grams}:
            c[g[1:]] = c.get(g[1:], 0) + 1
        levels[m] = smooth(c)

    def p(gram):
        if not gram:
            return 1 / 4096
        c, d, total, left = levels[len(gram)]
        h, low = gram[:-1], p(gram[1:])
        if h not in total:
            return low
        v = c.get(gram, 0)
        return (v - d[min(v, 3)]) / total[h] + left[h] / total[h] * low

    return p


def split(key):
    return tuple(int(key) >> Q.BITS * (Q.ORDER - 1 - i) & 4095 for i in range(Q.ORDER))


def test_model_is_kneser_ney_and_sums_to_one(spark, monkeypatch):
    rng = np.random.default_rng(2)
    letters = lambda k: "".join(rng.choice(list("abc dЖ."), k, p=[0.3, 0.2, 0.1, 0.2, 0.1, 0.05, 0.05]))
    texts = [(letters(300), "x"), (letters(500), "x"), (letters(200), None), ("", "x"), (None, "y")]
    docs = spark.createDataFrame([(i, t, x) for i, (t, x) in enumerate(texts)], "doc_id long, text string, lang string").repartition(2)
    for shard, held in ((Q.SHARD, Q.HELD), (60, 50)):
        monkeypatch.setattr(Q, "SHARD", shard)
        monkeypatch.setattr(Q, "HELD", held)
        files = Q.train(docs)
        assert files.keys() == {"1x", "0"} and (len(files["1x"]) > 2) == (shard == 60)
        models = Q.Models(files)
        for lang, own in (("1x", texts[:2]), ("0", texts[2:3])):
            keys = np.concatenate([Q.gram_keys(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t.encode())]))[0] for t, _ in own])
            seen, counts = np.unique(keys, return_counts=True)
            p = brute_kneser_ney([split(k) for k in seen], counts.tolist())
            odd = rng.choice([97, 98, 32, 0x416, 4000], (80, Q.ORDER)).astype(np.uint64)
            some = np.concatenate([seen, sum(odd[:, i] << np.uint64(Q.BITS * (Q.ORDER - 1 - i)) for i in range(Q.ORDER))])
            assert np.allclose(np.exp(models.score(some, lang)), [p(split(k)) for k in some], rtol=1e-4)
        context = seen[5] >> np.uint64(Q.BITS)
        every = (context << np.uint64(Q.BITS)) | np.arange(4096, dtype=np.uint64)
        assert abs(np.exp(models.score(every, "0")).sum() - 1) < 1e-4
    assert Q.Models(files).score(seen[:3], "1unheard").tolist() == [Q._UNIFORM] * 3


def test_grams_end_at_each_character(monkeypatch):
    first = "Ab\tж9\n日é"
    raw = np.frombuffer((first + "xy").encode(), np.uint8)
    offsets = np.array([0, len(first.encode()), len(first.encode()), len(raw)])
    keys, n = Q.gram_keys(raw, offsets, 5)
    assert n.tolist() == [8, 0, 2]
    e, parts = Q.EDGE, lambda k: tuple(int(k) >> 12 * (4 - i) & 4095 for i in range(5))
    assert parts(keys[0]) == (e, e, e, e, 65) and parts(keys[4]) == (65, 98, 32, 0x436, 48) and parts(keys[8]) == (e, e, e, e, 120)
    assert parts(keys[6])[-1] >= 0x800 and parts(keys[7])[-1] == 0xE9
    for dense in (Q.DENSE, 30, 0):
        monkeypatch.setattr(Q, "DENSE", dense)
        for order in (1, 3, 5):
            grams, which, m = Q.distinct_grams(raw, offsets, order)
            assert grams[which].tolist() == Q.gram_keys(raw, offsets, order)[0].tolist() and m.tolist() == n.tolist()


def test_passages_in_another_language_are_no_fault(spark):
    rng = np.random.default_rng(5)
    prose = lambda letters, k: " ".join("".join(rng.choice(list(letters), rng.integers(2, 8))) for _ in range(k))
    rows = [(i, prose("etaoinsr" if i % 2 else "жищуклмд", 150), ("en", "ru")[1 - i % 2]) for i in range(200)]
    rows += [(500, prose("etaoinsr", 100) + " " + prose("жищуклмд", 60), "en")]
    got = {r.doc_id: r for r in Q.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert got[500].log_ppl < got[500].high


def test_query_edges_and_groups(spark, monkeypatch):
    rng = np.random.default_rng(1)
    prose = lambda k: " ".join("".join(rng.choice(list("etaoinsr"), rng.integers(2, 8))) for _ in range(k))
    rows = [(i, prose(200), ("en", "de", None)[i % 3], "c", "c") for i in range(150)]
    rows += [(900, "$#q%X " * 200, "en", "c", "c"), (901, None, "en", None, None), (902, "", None, None, None), (903, "\n".join([prose(60)] * 3), "de", None, None), (None, prose(100), "en", None, None), (904, prose(60000), "xx", None, None), rows[0]]
    rows += [(905, "".join(map(str, rng.integers(0, 10, 30))) + " QQ%%zz" * 3 + prose(30).upper().replace("E", "Z"), "en", None, None)]
    df = spark.createDataFrame(rows, SCHEMA).repartition(3)
    want = {r[0]: brute(r[1]) for r in rows if r[0] != 904}
    results = []
    for limit, shard in ((Q.MODEL_BYTES, Q.SHARD), (1, 3000)):
        monkeypatch.setattr(Q, "MODEL_BYTES", limit)
        monkeypatch.setattr(Q, "SHARD", shard)
        got = Q.quality_rules(df).collect()
        assert len(got) == len(rows)
        by = {r.doc_id: r for r in got}
        for i, w in want.items():
            assert (by[i].n_words, by[i].word_chars, by[i].n_symbols, by[i].n_dup_lines, by[i].n_repeat_words) == w
        assert not any(by[i].kept for i in (900, 901, 902, 903, 905)) and by[903].base_failed and not by[905].base_failed
        assert sum(by[i].kept for i in range(150)) >= 148 and by[None].kept
        results.append(sorted((str(r.doc_id), r.kept, round(r.log_ppl or 0, 9)) for r in got))
    assert results[0] == results[1]
    assert Q.quality_rules(df.limit(0)).count() == 0
