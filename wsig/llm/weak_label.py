"""Operator 2, quality classifier from weak labels.

Overlapping heuristic labellers vote good, bad or nothing on every document. Spark counts the vote patterns of all
documents; expectation-maximisation over the patterns estimates the share of good documents and, for each labeller, how often it
votes what under either class, so labellers are weighed by their accuracy rather than counted. The posterior of its pattern labels a document.
A bounded sample of documents (the ``SAMPLE`` smallest hashes of id and text) with posterior labels trains a linear scorer over
hashed character 4-grams, which then scores every document. A second scorer learns a
given label (toxicity) from a bounded sample (``LABELLED``, likewise) of labelled documents, over hashed words and their beginnings.
What is drawn depends on the rows alone, not on how they are dealt, so reruns agree.

A null or empty text gets the votes of an empty document (bad). Rows with a null id are scored too but never sampled.
Repeated rows are scored alike and sampled once; of several labels of one id the greatest counts. With no labelled rows the second score is null. An empty table gives an empty result.
Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.llm import shared
from wsig.llm.quality_rules import base_rules, gram_keys
from wsig.llm.textscan import Scan, mix, steps

SAMPLE, LABELLED, BITS, STEPS = 6_000, 6_000, 18, 60
_SIZE = 1 << BITS

# Frequent function words of the corpus's languages.
_FUNCTION_WORDS = "the of and to in is was for on that with are it as be der die und in den von zu das mit sich des auf für ist nicht ein eine de la le et les des en un du une que dans est pour qui el los las y una por con para se".split()

LABELLERS = ("length", "symbols", "repeats", "duplicate_lines", "capitals", "word_length", "function_words", "bars", "shouts")


def _hash_words(words: list[str]) -> np.ndarray:
    scan = Scan(pa.array(words))
    return np.sort(scan.word_hash())


_FUNCTION_HASHES = _hash_words(sorted(set(_FUNCTION_WORDS)))


def votes(scan: Scan) -> np.ndarray:
    """A row for each document, a column for each labeller: 0 nothing, 1 bad, 2 good."""
    base = base_rules(scan)
    n = np.maximum(base["n_words"], 1)
    text = scan.bytes
    upper = scan.per_doc((text >= 65) & (text <= 90)) / np.maximum(base["word_chars"], 1)
    known = _FUNCTION_HASHES
    h = scan.word_hash()
    function = scan.words_per_doc(known[np.minimum(np.searchsorted(known, h), len(known) - 1)] == h) / n
    length = base["word_chars"] / n
    single = scan.ends - scan.starts == 1
    bars = scan.words_per_doc(single & (text[scan.starts] == ord("|"))) / n
    shouts = scan.words_per_doc(text[scan.ends - 1] == ord("!")) / n
    marks = base["n_symbols"] / n
    repeats = base["n_repeat_words"] / n

    def vote(bad, good):
        return np.where(bad, 1, np.where(good, 2, 0))

    return np.stack(
        [
            vote(base["n_words"] < 5, base["n_words"] >= 60),
            vote(marks > 0.25, marks < 0.01),
            vote(repeats > 0.25, repeats == 0),
            vote(base["n_dup_lines"] >= 3, base["n_dup_lines"] == 0),
            vote(upper > 0.25, (upper > 0.002) & (upper < 0.08)),
            vote((length > 9) | (length < 2.5), (length > 3.5) & (length < 7.5)),
            vote(function < 0.05, function > 0.15),
            vote(bars > 0.1, bars == 0),
            vote(shouts > 0.2, shouts < 0.02),
        ],
        axis=1,
    ).astype(np.int8)


def patterns(v: np.ndarray) -> np.ndarray:
    """One number for each row of votes."""
    return v.astype(np.int64) @ (3 ** np.arange(v.shape[1]))


class LabelModel:
    """Naive Bayes over votes with hidden classes, by EM on pattern counts."""

    def __init__(self, pattern: np.ndarray, count: np.ndarray, labellers: int, rounds: int = 100):
        self.labellers = labellers
        v = pattern[:, None] // 3 ** np.arange(labellers) % 3
        good = (v == 2).sum(axis=1) + 1.0
        q = np.clip(good / (good + 2.5 * (v == 1).sum(axis=1) + 0.5), 0.02, 0.98)
        for _ in range(rounds):
            self.prior = float(np.clip((q * count).sum() / max(count.sum(), 1), 1e-4, 1 - 1e-4))
            table = np.zeros((2, labellers, 3))
            for y, w in ((0, (1 - q) * count), (1, q * count)):
                for value in range(3):
                    table[y, :, value] = ((v == value) * w[:, None]).sum(axis=0) + 0.5
                table[y] /= table[y].sum(axis=1, keepdims=True)
            self.table = table
            new = self.posterior(pattern)
            done = np.abs(new - q).max(initial=0) < 1e-9
            q = new
            if done:
                break

    def posterior(self, pattern: np.ndarray) -> np.ndarray:
        v = pattern[:, None] // 3 ** np.arange(self.labellers) % 3
        at = np.arange(self.labellers)
        odds = np.log(self.prior / (1 - self.prior)) + (np.log(self.table[1, at, v]) - np.log(self.table[0, at, v])).sum(axis=1)
        return 1 / (1 + np.exp(-np.clip(odds, -50, 50)))

    def accuracies(self) -> np.ndarray:
        """For each labeller, how often it is right when it votes."""
        right = self.prior * self.table[1, :, 2] + (1 - self.prior) * self.table[0, :, 1]
        return right / (right + self.prior * self.table[1, :, 1] + (1 - self.prior) * self.table[0, :, 2])


_BARE = np.arange(256, dtype=np.uint8)
_BARE[:128] = [ord(chr(i).lower()) if chr(i).isalnum() else 0x20 for i in range(128)]


#: Bytes of a word's beginning that are features beside the whole word, as invented and inflected words share them.
PREFIXES = (5, 6, 7, 8)


def _counted(part: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, feature and count from (document << 32 | feature), sorted."""
    part = np.sort(part)
    first = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1]))) if len(part) else np.zeros(0, np.int64)
    count = np.diff(np.append(first, len(part)))
    part = part[first]
    return (part >> np.uint64(32)).astype(np.int64), (part & np.uint64(0xFFFFFFFF)).astype(np.int64), count


def features(scan: Scan) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sparse rows: document, hashed 4-gram, square root of its count, each document of norm 1."""
    keys, n = gram_keys(scan.bytes, scan.offsets, 4)
    doc, at, count = _counted(np.repeat(np.arange(len(n), dtype=np.uint64), n) << np.uint64(32) | mix(keys) & np.uint64(_SIZE - 1))
    value = np.sqrt(count.astype(float))
    norm = np.sqrt(np.bincount(doc, value**2, len(n)))
    return doc, at, (value / np.maximum(norm[doc], 1e-12)).astype(np.float32)


def word_features(scan: Scan) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sparse rows: document, hashed word or beginning of a word (lower case, without ASCII marks), log of 1 + count."""
    bare = Scan(None, (_BARE[scan.bytes], scan.offsets))
    parts = [bare.doc.astype(np.uint64) << np.uint64(32) | bare.word_hash() & np.uint64(_SIZE - 1)]
    for k in PREFIXES:
        long = bare.ends - bare.starts > k
        h = mix(bare.hash_runs(bare.starts[long], bare.starts[long] + k) + np.uint64(k))
        parts.append(bare.doc[long].astype(np.uint64) << np.uint64(32) | h & np.uint64(_SIZE - 1))
    doc, at, count = _counted(np.concatenate(parts))
    return doc, at, np.log1p(count).astype(np.float32)


class Scorer:
    """Logistic regression over hashed features, trained by full-batch Adagrad."""

    def __init__(self, doc: np.ndarray, at: np.ndarray, value: np.ndarray, label: np.ndarray, l2: float = 1e-5, rounds: int = STEPS):
        w, g2, bias, b2 = np.zeros(_SIZE), np.full(_SIZE, 1e-8), 0.0, 1e-8
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-np.clip(np.bincount(doc, w[at] * value, len(label)) + bias, -30, 30)))
            e = (p - label) / len(label)
            g = np.bincount(at, e[doc] * value, _SIZE) + l2 * w
            g2 += g**2
            b2 += e.sum() ** 2
            w -= 0.5 * g / np.sqrt(g2)
            bias -= 0.5 * e.sum() / np.sqrt(b2)
        self.w, self.bias = w.astype(np.float32), float(bias)

    @classmethod
    def selected(cls, doc: np.ndarray, at: np.ndarray, value: np.ndarray, label: np.ndarray, z: float = 5.0) -> Scorer:
        """Over features only that occur with the label ``z`` standard deviations more or less often than by chance."""
        share = np.clip(label.mean(), 1e-4, 1 - 1e-4)
        n = np.bincount(at, minlength=_SIZE)
        off = (np.bincount(at, label[doc], _SIZE) - n * share) / np.sqrt(np.maximum(n, 1) * share * (1 - share))
        keep = (np.abs(off) >= z)[at]
        return cls(doc[keep], at[keep], value[keep], label, l2=1e-4, rounds=400)

    def score(self, doc: np.ndarray, at: np.ndarray, value: np.ndarray, n: int) -> np.ndarray:
        return np.bincount(doc, self.w[at] * value, n) + self.bias


def _sampled(docs: DataFrame, column: str, kind=features) -> tuple[np.ndarray, ...] | None:
    """Features and labels of a bounded number of rows (text, column), on the driver."""

    def run(batches):
        for batch in steps(batches):
            scan = Scan(batch.column("text"))
            doc, at, value = kind(scan)
            edges = pa.array(np.searchsorted(doc, np.arange(batch.num_rows + 1)).astype(np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(column), pa.ListArray.from_arrays(edges, pa.array(at.astype(np.int32))), pa.ListArray.from_arrays(edges, pa.array(value)), batch.column("draw")], ["label", "at", "value", "draw"])

    rows = docs.select("text", F.col(column).cast("double").alias(column), "draw").mapInArrow(run, "label double, at array<int>, value array<float>, draw long").toArrow().sort_by("draw")
    if not rows.num_rows:
        return None
    at = rows.column("at").combine_chunks()
    doc = np.repeat(np.arange(rows.num_rows, dtype=np.int32), np.diff(at.offsets.to_numpy()))
    return doc, at.flatten().to_numpy(), rows.column("value").combine_chunks().flatten().to_numpy(), rows.column("label").to_numpy()


def _draw(drawn: DataFrame, n: int, most: int) -> DataFrame:
    """The ``most`` smallest different values of ``draw``; of ``n`` rows only those that can be among them are sorted."""
    low = F.shiftrightunsigned("draw", 1) <= F.lit((2**63 - 1) * min(n, 2 * most) // max(n, 1))
    return drawn.where(low & F.col("doc_id").isNotNull()).dropDuplicates(["draw"]).orderBy(F.shiftrightunsigned("draw", 1), "draw").limit(most)


def weak_label_quality(docs: DataFrame, labels: DataFrame | None = None, label: str = "toxic") -> DataFrame:
    """doc_id, pattern, posterior, score, kept and, with ``labels`` (doc_id, label), label_score and flagged."""
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long"), "text")
    keyed = rows.withColumn("draw", F.xxhash64("doc_id", "text", F.lit(23)))

    def vote(batches):
        for batch in steps(batches):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("draw"), pa.array(patterns(votes(Scan(batch.column("text")))))], ["doc_id", "draw", "pattern"])

    voted, path = shared.settle(keyed.mapInArrow(vote, "doc_id long, draw long, pattern long"), "votes")
    counts = voted.groupBy("pattern").agg(F.count("*").alias("n")).toArrow().sort_by("pattern")  # at most 3 ** labellers rows
    pattern, n = counts.column("pattern").to_numpy(), counts.column("n").to_numpy()
    model = LabelModel(pattern, n, len(LABELLERS))

    def labelled(batches):
        for batch in steps(batches):
            q = model.posterior(patterns(votes(Scan(batch.column("text")))))
            yield pa.RecordBatch.from_arrays([batch.column("text"), pa.array(q), batch.column("draw")], ["text", "posterior", "draw"])

    texts_of = lambda chosen: keyed.join(F.broadcast(chosen), "draw").dropDuplicates(["draw"])  # noqa: E731  (SAMPLE or LABELLED rows)
    drawn = _sampled(texts_of(_draw(voted, int(n.sum()), SAMPLE).select("draw")).select("text", "draw").mapInArrow(labelled, "text string, posterior double, draw long"), "posterior")
    quality = Scorer(*drawn) if drawn else None
    other = None
    if labels is not None:
        known = labels.select(F.col("doc_id").cast("long"), F.col(label).cast("double").alias(label)).where(F.col(label).isNotNull()).groupBy("doc_id").agg(F.max(label).alias(label))
        marked, marked_path = shared.settle(voted.select("doc_id", "draw").join(known, "doc_id"), "labelled")
        chosen = _draw(marked, marked.count(), LABELLED).select("draw", label)
        drawn = _sampled(texts_of(chosen).select("text", label, "draw"), label, word_features)
        other = Scorer.selected(*drawn) if drawn else None
        shared.drop(spark, marked_path)
    shared.drop(spark, path)
    sent = spark.sparkContext.broadcast((model, quality, other))

    def score(batches):
        model, quality, other = sent.value
        for batch in steps(batches):
            scan = Scan(batch.column("text"))
            pattern = patterns(votes(scan))
            doc, at, value = features(scan)
            none = pa.nulls(batch.num_rows, pa.float64())
            s = pa.array(quality.score(doc, at, value, batch.num_rows)) if quality else none
            t = pa.array(other.score(*word_features(scan), batch.num_rows)) if other else none
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(pattern), pa.array(model.posterior(pattern)), s, t], ["doc_id", "pattern", "posterior", "score", "label_score"])

    out = rows.mapInArrow(score, "doc_id long, pattern long, posterior double, score double, label_score double")
    return out.select("doc_id", "pattern", "posterior", "score", (F.coalesce("score", F.lit(-1.0)) >= 0).alias("kept"), "label_score", (F.coalesce("label_score", F.lit(-1.0)) >= 0).alias("flagged"))
