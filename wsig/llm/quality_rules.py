"""Operator 1, quality rules: n-gram perplexity under a corpus-counted model, with bands for each language.

Spark counts the character n-grams (1 to ``ORDER``) of all documents and makes from them, in joins and aggregates, an interpolated
modified Kneser-Ney model for each language: log probabilities of the seen n-grams and the weights by which their contexts pass to
shorter ones. Characters are code points (case and digits folded; from U+0800 on hashed to 2048 classes), so a model grows with
the corpus and its scripts and has no fixed size. Its entries are dealt to shards of about ``SHARD`` by the two characters before
the last, which all but the shortest n-grams of a place share, and each shard is a file of sorted hash arrays in the folder that the
cluster shares: 64-bit keys, a bijection of the n-gram, with their values, and a directory by leading bits. Tasks
score the distinct n-grams of a step of text shard by shard and hold at most ``MODEL_BYTES`` of shards; neither the driver nor a broadcast holds a model.

A stretch of ``STRETCH`` characters counts under the language that reads it best, so that passages quoted from another language are no
fault of a document. A document is kept if it passes the base rules and its log perplexity lies within its language's band
(median minus/plus a number of robust standard deviations, wider for shorter texts, as their mean log probability
varies more). Null language: a language of its own. Null or empty text: no words, so the base rules reject it.
Repeated rows are judged alike, each for itself. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsig.llm import shared
from wsig.llm.textscan import STEP, Scan, as_bytes, mix, steps, windows

BITS, ORDER = 12, 3
# The order is 3: the corpus's own junk is counted with the rest, and longer n-grams learn to read it.
#: Entries of a shard, and bytes of shards that a worker holds.
SHARD, MODEL_BYTES = 4_000_000, 192 << 20
#: Distinct n-grams that a counting task holds before it passes them on.
HELD = 2_000_000
#: Codes that are numbered by a table rather than by sorting.
DENSE = 1 << 23
#: Characters of a stretch that is scored under the language that reads it best, among the document's and the ``READ`` with the largest models.
STRETCH, READ = 64, 8
#: Robust standard deviations from a language's median that a document's log perplexity may lie off, below and above.
BAND = (4.0, 3.0)
MIN_WORDS, REPEAT_WINDOW, MAX_REPEAT_PERCENT = 20, 8, 30
SYMBOLS = b"#*$%&|<>"
EDGE = 10
_CLASS = (1 << BITS) - 1
_PAIR = (1 << 2 * BITS) - 1
#: An entry's code: n-gram (60 bits), its length (3 bits), and a sign for contexts.
_LENGTH, _CONTEXT = 60, 1 << 63
_UNIFORM = -float(np.log(1 << BITS))


def classes() -> np.ndarray:
    """Class of every code point: itself up to U+07FF, with capitals, digits and line ends folded; a hash of it beyond."""
    out = np.arange(0x110000, dtype=np.uint64)
    out[0x800:] = 0x800 + ((out[0x800:] * np.uint64(2654435761)) >> np.uint64(7)) % np.uint64(0x800)
    for i in range(0x800):
        c = chr(i)
        out[i] = ord("A") if c.isupper() else ord("0") if c.isdigit() else i
    out[9] = 0x20
    out[10:14] = EDGE
    return out


_CLASSES = classes()


def gram_keys(text: np.ndarray, offsets: np.ndarray, order: int = ORDER) -> tuple[np.ndarray, np.ndarray]:
    """The key of the n-gram that ends at each character, and each document's number of characters."""
    points = np.frombuffer(text.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    leads = np.zeros(len(text) + 1, np.int64)
    np.cumsum((text & 0xC0) != 0x80, out=leads[1:])
    n = np.diff(leads[offsets])
    doc = np.repeat(np.arange(len(n)), n)
    at = np.arange(len(points)) + (order - 1) * (doc + 1)
    line = np.full(len(points) + (order - 1) * (len(n) + 1), EDGE, np.uint64)
    line[at] = _CLASSES[points]
    keys = np.zeros(len(points), np.uint64)
    for back in range(order):
        keys |= line[at - back] << np.uint64(BITS * back)
    return keys, n


def distinct_grams(text: np.ndarray, offsets: np.ndarray, order: int = ORDER) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The different n-grams, which of them ends at each character, and each document's number of characters.

    Characters, pairs, triples ... are numbered one after the other, so that no n-gram needs sorting while its number times
    the alphabet stays small.
    """
    points = np.frombuffer(text.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    leads = np.zeros(len(text) + 1, np.int64)
    np.cumsum((text & 0xC0) != 0x80, out=leads[1:])
    n = np.diff(leads[offsets])
    at = np.arange(len(points)) + (order - 1) * (np.repeat(np.arange(len(n)), n) + 1)
    line = np.full(len(points) + (order - 1) * (len(n) + 1), EDGE, np.int64)
    line[at] = _CLASSES[points]
    alphabet, own = _numbered(line, 1 << BITS)
    grams, which = alphabet.astype(np.uint64), own
    for _ in range(1, order):
        code = np.empty(len(own), np.int64)
        code[0] = 0
        np.multiply(which[:-1], len(alphabet), out=code[1:])
        code += own
        seen, which = _numbered(code, len(grams) * len(alphabet))
        grams = (grams[seen // len(alphabet)] << np.uint64(BITS)) | alphabet[seen % len(alphabet)].astype(np.uint64)
    return grams, which[at], n


def _numbered(code: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The different codes, ascending, and the place of each among them."""
    if size > DENSE:
        return np.unique(code, return_inverse=True)
    there = np.zeros(size, bool)
    there[code] = True
    seen = np.flatnonzero(there)
    number = np.zeros(size, np.int32)
    number[seen] = np.arange(len(seen), dtype=np.int32)
    return seen, number[code]


def language(lang: str | None) -> str:
    """A language's name in the model: null differs from every string."""
    return "0" if lang is None else "1" + lang


def by_language(batch: pa.RecordBatch) -> dict[str, np.ndarray]:
    """Rows of each language of a batch."""
    order: dict[str, list[int]] = {}
    for i, x in enumerate(batch.column("lang").to_pylist()):
        order.setdefault(language(x), []).append(i)
    return {k: np.array(v) for k, v in order.items()}


def _places(n: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Where the characters of some documents are."""
    lengths = n[rows]
    firsts = (np.cumsum(n) - n)[rows]
    return np.arange(int(lengths.sum())) + np.repeat(firsts - (np.cumsum(lengths) - lengths), lengths)


def tally(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sums of counts by key, keys ascending."""
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    new = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, np.int64)
    return keys[new], np.add.reduceat(counts, new) if len(new) else counts


class Counter:
    """n-gram counts by language of the documents that one task has seen since it last passed them on."""

    def __init__(self):
        self.parts: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
        self.held = 0

    def add(self, batch: pa.RecordBatch) -> None:
        grams, which, n = distinct_grams(*as_bytes(batch.column("text")))
        for lang, rows in by_language(batch).items():
            counts = np.bincount(which[_places(n, rows)], minlength=len(grams))
            seen = np.flatnonzero(counts)
            self.parts.setdefault(lang, []).append((grams[seen], counts[seen]))
            self.held += len(seen)
        if self.held > HELD:
            self.parts = {lang: [self._sum(mine)] for lang, mine in self.parts.items()}
            self.held = sum(len(mine[0][0]) for mine in self.parts.values())

    @staticmethod
    def _sum(parts):
        return tally(np.concatenate([k for k, _ in parts]), np.concatenate([c for _, c in parts]))

    def rows(self):
        for lang, parts in self.parts.items():
            keys, counts = self._sum(parts)
            for i in range(0, len(keys), 1 << 16):
                k, c = keys[i : i + (1 << 16)], counts[i : i + (1 << 16)]
                yield pa.RecordBatch.from_arrays([pa.array([lang]).take(pa.array(np.zeros(len(k), np.int32))), pa.array(k.view(np.int64)), pa.array(c.astype(np.int64))], ["lang", "gram", "n"])
        self.parts, self.held = {}, 0


def count_grams(docs: DataFrame) -> DataFrame:
    """(lang, gram, n) over all documents: each task sums its own n-grams before the shuffle."""

    def run(batches):
        counter = Counter()
        for batch in steps(batches):
            counter.add(batch)
            if counter.held > HELD // 2:  # even after summing
                yield from counter.rows()
        yield from counter.rows()

    part = docs.select("lang", "text").mapInArrow(run, "lang string, gram long, n long")
    return part.groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def _discounts(level: DataFrame) -> DataFrame:
    """(lang, d1, d2, d3): modified Kneser-Ney discounts of counts 1, 2 and 3 or more, a row for each language."""
    number = [F.greatest(F.lit(1), F.sum((F.col("n") == i).cast("long"))).alias(f"n{i}") for i in range(1, 5)]
    rows = level.groupBy("lang").agg(*number).withColumn("y", F.col("n1") / (F.col("n1") + 2 * F.col("n2")))
    d = [F.least(F.lit(most), F.greatest(F.lit(0.0), F.lit(i) - F.lit(i + 1) * F.col("y") * F.col(f"n{i + 1}") / F.col(f"n{i}"))).alias(f"d{i}") for i, most in ((1, 0.95), (2, 1.9), (3, 2.85))]
    return rows.select("lang", *d)


def _low(gram: str, m: int) -> Column:
    """The last m characters of n-grams."""
    return F.col(gram).bitwiseAND(F.lit((1 << BITS * m) - 1))


def smoothed(level: DataFrame, m: int, lower: DataFrame | None) -> DataFrame:
    """(lang, gram, p, context, weight) of the m-grams of ``level`` (lang, gram, n), interpolated with the (m - 1)-grams of ``lower``."""
    d = F.when(F.col("n") == 1, F.col("d1")).when(F.col("n") == 2, F.col("d2")).otherwise(F.col("d3"))
    rows = level.join(F.broadcast(_discounts(level)), "lang").select("lang", "gram", "n", d.alias("d"), F.shiftright("gram", BITS).alias("context"))
    sums = rows.groupBy("lang", "context").agg(F.sum("n").alias("total"), F.sum("d").alias("left"))
    rows = rows.join(sums, ["lang", "context"]).withColumn("weight", F.col("left") / F.col("total"))
    own = (F.col("n") - F.col("d")) / F.col("total")
    if lower is None:
        return rows.select("lang", "gram", (own + F.col("weight") / F.lit(float(1 << BITS))).alias("p"), "context", "weight")
    shorter = lower.select("lang", F.col("gram").alias("short"), F.col("p").alias("p_short"))
    return rows.withColumn("short", _low("gram", m - 1)).join(shorter, ["lang", "short"]).select("lang", "gram", (own + F.col("weight") * F.col("p_short")).alias("p"), "context", "weight")


def entries(counts: DataFrame) -> DataFrame:
    """(lang, code, value, pair) of all languages' models: log probabilities of n-grams and log weights of contexts.

    ``pair`` is the two characters by which an entry is dealt to a shard, null if every shard has it.
    """
    spark = counts.sparkSession
    levels, paths = {}, []

    def keep(df: DataFrame, tag: str) -> DataFrame:
        out, path = shared.settle(df, tag)
        paths.append(path)
        return out

    levels[ORDER] = keep(counts, f"grams-{ORDER}")
    for m in range(ORDER - 1, 0, -1):  # how many different characters come before
        levels[m] = keep(levels[m + 1].groupBy("lang", _low("gram", m).alias("gram")).agg(F.count("*").alias("n")), f"grams-{m}")
    lower, parts = None, []
    for m in range(1, ORDER + 1):
        lower = keep(smoothed(levels[m], m, lower), f"smoothed-{m}")
        pair = lambda c, some: c.bitwiseAND(F.lit(_PAIR)) if some else F.lit(None).cast("long")
        parts.append(lower.select("lang", F.col("gram").bitwiseOR(F.lit(m << _LENGTH)).alias("code"), F.log("p").cast("float").alias("value"), pair(F.shiftright("gram", BITS), m > 2).alias("pair")))
        contexts = lower.groupBy("lang", "context").agg(F.max("weight").alias("weight"))
        code = F.col("context").bitwiseOR(F.lit(((m - 1) << _LENGTH | _CONTEXT) - (1 << 64)))
        parts.append(contexts.select("lang", code.alias("code"), F.log(F.greatest("weight", F.lit(1e-12))).cast("float").alias("value"), pair(F.col("context"), m > 2).alias("pair")))
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    out, _ = shared.settle(out, "model-entries")
    shared.drop(spark, *paths)
    return out


def _spread(pair, shards):
    """The shard of a pair of characters, as write_model deals them."""
    return (pair * 40503 >> 8) % shards


def _store(path: str, data: tuple[np.ndarray, np.ndarray] | None = None):
    """Writes or reads a shard: the number of entries, the ascending keys, the values."""
    from pyarrow import fs

    store, inside = fs.FileSystem.from_uri(path)
    if data is not None:
        store.create_dir(inside.rpartition("/")[0], recursive=True)
        with store.open_output_stream(inside) as out:
            out.write(np.array([len(data[0])], "<u8").tobytes() + data[0].astype("<u8").tobytes() + data[1].astype("<f4").tobytes())
        return None
    with store.open_input_stream(inside) as file:
        raw = file.read()
    n = int(np.frombuffer(raw, "<u8", 1)[0])
    return np.frombuffer(raw, "<u8", n, 8), np.frombuffer(raw, "<f4", n, 8 + 8 * n)


def write_model(counts: DataFrame) -> dict[str, list[tuple[str, int]]]:
    """Writes the models' shards; returns each language's files in order of shard, and their numbers of entries."""
    spark = counts.sparkSession
    made = entries(counts)
    # a row of a few numbers for each language
    shards = made.groupBy("lang").agg(F.ceil(F.count("*") / SHARD).cast("int").alias("shards"))
    own = F.when(F.col("pair").isNotNull(), F.array(F.shiftright(F.col("pair") * 40503, 8) % F.col("shards"))).otherwise(F.sequence(F.lit(0).cast("long"), F.col("shards").cast("long") - 1))
    dealt = made.join(F.broadcast(shards), "lang").select("lang", F.explode(own).alias("shard"), "code", "value")
    folder = shared.new_path(spark, "model")

    def run(batches):
        held, key = [], None

        def close():
            codes = mix(np.concatenate([c for c, _ in held]).view(np.uint64))
            order = np.argsort(codes)
            path = f"{folder}/{uuid.uuid4().hex}.grams"
            _store(path, (codes[order], np.concatenate([v for _, v in held])[order]))
            return pa.RecordBatch.from_arrays([pa.array([x]) for x in (*key, path, len(codes))], ["lang", "shard", "path", "n"])

        for batch in batches:
            langs, numbers = batch.column("lang").to_pylist(), batch.column("shard").to_numpy()
            code, value = batch.column("code").to_numpy(), batch.column("value").to_numpy()
            edges = [0, *[i for i in range(1, len(langs)) if langs[i] != langs[i - 1] or numbers[i] != numbers[i - 1]], len(langs)]
            for a, b in zip(edges, edges[1:]):
                if b > a:
                    if key is not None and key != (langs[a], int(numbers[a])):
                        yield close()
                        held = []
                    key = (langs[a], int(numbers[a]))
                    held.append((code[a:b], value[a:b]))
        if held:
            yield close()

    sorted_rows = dealt.repartition(shared.slots(spark), "lang", "shard").sortWithinPartitions("lang", "shard")
    manifest, _ = shared.settle(sorted_rows.mapInArrow(run, "lang string, shard long, path string, n long"), "model-manifest")
    out: dict[str, list[tuple[str, int]]] = {}
    for r in manifest.orderBy("lang", "shard").collect():  # a row for each language and each SHARD entries
        out.setdefault(r["lang"], []).append((r["path"], r["n"]))
    return out


class Table:
    """A shard's sorted hash array, found through a directory of the keys' leading bits."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.keys, self.values = np.append(keys, np.uint64((1 << 64) - 1)), np.append(values, np.float32(0))
        bits = max(1, len(keys).bit_length())
        self.shift = np.uint64(64 - bits)
        self.first = np.searchsorted(keys, np.arange(1 << bits, dtype=np.uint64) << self.shift).astype(np.int32)

    def find(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each code is there, and its value."""
        h = mix(codes)
        at = self.first[(h >> self.shift).astype(np.int64)]
        behind = np.flatnonzero(self.keys[at] < h)
        while len(behind):
            at[behind] += 1
            behind = behind[self.keys[at[behind]] < h[behind]]
        return (self.keys[at] == h) & (at < len(self.keys) - 1), self.values[at]


class Models:
    """Scores n-grams by shards that are read when needed."""

    def __init__(self, files: dict[str, list[tuple[str, int]]], read=None):
        self.files, self.read = files, read or (lambda path: Table(*_store(path)))
        self.kept: dict[str, Table] = {}
        size = {lang: sum(n for _, n in shards) for lang, shards in files.items()}
        #: The languages with the largest models.
        self.often = sorted(size, key=lambda x: (-size[x], x))[:READ]

    @property
    def nbytes(self) -> int:
        return 20 * sum(n for shards in self.files.values() for _, n in shards)

    def table(self, path: str, n: int) -> Table:
        if path not in self.kept:
            while self.kept and 20 * (n + sum(len(t.keys) for t in self.kept.values())) > MODEL_BYTES:
                self.kept.pop(next(iter(self.kept)))
            self.kept[path] = self.read(path)
        return self.kept[path]

    def score(self, grams: np.ndarray, lang: str) -> np.ndarray:
        """Log probability of the last character of each n-gram given those before it."""
        files = self.files.get(lang, [])
        if not len(files):
            return np.full(len(grams), _UNIFORM)
        if len(files) == 1:
            return self._score(grams, self.table(*files[0]))
        out = np.zeros(len(grams))
        shard = _spread(((grams >> np.uint64(BITS)) & np.uint64(_PAIR)).astype(np.int64), len(files))
        for i, file in enumerate(files):
            mine = np.flatnonzero(shard == i)
            if len(mine):
                out[mine] = self._score(grams[mine], self.table(*file))
        return out

    @staticmethod
    def _score(grams: np.ndarray, table: Table) -> np.ndarray:
        out, left = np.zeros(len(grams)), np.arange(len(grams))
        for m in range(ORDER, 0, -1):
            short = grams[left] & np.uint64((1 << BITS * m) - 1)
            seen, value = table.find(short | np.uint64(m << _LENGTH))
            out[left[seen]] += value[seen]
            left, short = left[~seen], short[~seen]
            if not len(left):
                return out
            known, weight = table.find((short >> np.uint64(BITS)) | np.uint64((m - 1) << _LENGTH | _CONTEXT))
            out[left[known]] += weight[known]
        out[left] += _UNIFORM
        return out


def base_rules(scan: Scan) -> dict[str, np.ndarray]:
    """Counts of the base rules for each document of a scan."""
    text = scan.bytes
    lead = (text & 0xC0) != 0x80
    symbol = np.zeros(256, bool)
    symbol[list(SYMBOLS)] = True
    out = {"n_words": scan.n_words, "word_chars": scan.per_doc(lead & scan.solid), "n_symbols": scan.per_doc(symbol[text])}
    # lines: between the document's edges and its line feeds; only those with a word
    feeds = np.flatnonzero(text == 10)
    starts = np.sort(np.concatenate([scan.offsets[:-1], feeds + 1]))
    ends = np.sort(np.concatenate([scan.offsets[1:], feeds]))
    doc = np.sort(np.concatenate([np.arange(len(scan.n_words)), np.searchsorted(scan.offsets, feeds, "right") - 1]))
    words = np.searchsorted(scan.starts, ends) > np.searchsorted(scan.starts, starts)
    starts, ends, doc = starts[words], ends[words], doc[words]
    lines = mix(scan.hash_runs(starts, ends) + doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    _, first = np.unique(lines, return_index=True)
    n_docs = len(scan.n_words)
    out["n_dup_lines"] = np.bincount(doc, minlength=n_docs) - np.bincount(doc[first], minlength=n_docs)
    at = scan.window_starts(REPEAT_WINDOW)
    covered = np.zeros(len(scan.doc) + 1, np.int64)
    if len(at):
        h = mix(windows(scan.word_hash(), at, REPEAT_WINDOW) + scan.doc[at].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        order = np.argsort(h)
        same = h[order[1:]] == h[order[:-1]]
        again = at[order[np.concatenate(([False], same)) | np.concatenate((same, [False]))]]
        np.add.at(covered, again, 1)
        np.add.at(covered, again + REPEAT_WINDOW, -1)
    out["n_repeat_words"] = scan.words_per_doc(np.cumsum(covered[:-1]) > 0)
    return out


_MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "log_ppl", "n_chars_scored")
_SCORED = ", ".join(f"{c} {'double' if c == 'log_ppl' else 'long'}" for c in _MEASURES)


def _measure(batch: pa.RecordBatch, models: Models) -> dict[str, np.ndarray]:
    """Base counts and log perplexity of a batch's rows."""
    scan = Scan(batch.column("text"))
    out = base_rules(scan)
    grams, which, n = distinct_grams(scan.bytes, scan.offsets)
    pieces = -(-n // STRETCH)  # stretches of each document
    ends = np.cumsum(n)
    firsts = np.repeat(ends - n, pieces) + STRETCH * (np.arange(int(pieces.sum())) - np.repeat(np.cumsum(pieces) - pieces, pieces))
    edges = np.append(firsts, len(which))
    best = np.full(len(firsts), -np.inf)

    def read(lang, places, some):
        sums = np.zeros(len(places) + 1)
        np.cumsum(models.score(grams, lang)[which[places]], out=sums[1:])
        lengths = np.diff(edges)[some]
        best[some] = np.maximum(best[some], np.diff(sums[np.append(0, np.cumsum(lengths))]))

    if len(firsts):
        whole, every = slice(None), np.arange(len(which))
        for lang in models.often:
            read(lang, every, whole)
        doc = np.repeat(np.arange(len(n)), pieces)
        for lang, rows in by_language(batch).items():
            if lang not in models.often:
                read(lang, _places(n, rows), np.flatnonzero(np.isin(doc, rows)))
    total = np.bincount(np.repeat(np.arange(len(n)), pieces), best, len(n))
    return out | {"log_ppl": np.where(n > 0, -total / np.maximum(n, 1), np.nan), "n_chars_scored": n}


def _sized(files: dict) -> int:
    """Bytes of text of a scoring step: more where shards have to be read again for each step."""
    return STEP if Models(files).nbytes <= MODEL_BYTES else 8 * STEP


def score(docs: DataFrame, files: dict) -> DataFrame:
    """Base counts and log perplexity for each document."""

    def run(batches):
        models = Models(files)
        for batch in steps(batches, size=_sized(files)):
            m = _measure(batch, models)
            columns = [pa.array(m[c], from_pandas=True) if c == "log_ppl" else pa.array(m[c].astype(np.int64)) for c in _MEASURES]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("lang"), *columns], ["doc_id", "lang", *_MEASURES])

    return docs.select(F.col("doc_id").cast("long"), "lang", "text").mapInArrow(run, f"doc_id long, lang string, {_SCORED}")


def train(docs: DataFrame) -> dict[str, list[tuple[str, int]]]:
    """The files of a Kneser-Ney model for each language, made from counts over all documents."""
    return write_model(count_grams(docs))


#: Standard deviation of one character's log probability, for the band of short texts.
CHAR_SD = 0.7


def bands(scored: DataFrame) -> DataFrame:
    """Median and robust spread of log perplexity by language, over all documents that pass the base rules."""
    q = F.percentile_approx("log_ppl", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), 10000)
    return scored.where(~base_failed()).groupBy("lang").agg(q.alias("q")).select(F.col("lang").alias("band_lang"), F.col("q")[1].alias("middle"), ((F.col("q")[2] - F.col("q")[0]) / 1.349).alias("spread"))


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (F.lit(100) * F.col("n_repeat_words") > F.lit(MAX_REPEAT_PERCENT) * F.col("n_words"))


def _judged(docs: DataFrame, band: tuple[float, float]) -> tuple[dict, DataFrame, DataFrame]:
    """The models' files, measures of all rows, and the languages' bands."""
    files = train(docs)
    scored, _ = shared.settle(score(docs, files), "scored")
    return files, scored, bands(scored)


def quality_rules(docs: DataFrame, band: tuple[float, float] = BAND) -> DataFrame:
    """One row for each row of ``docs``: doc_id, lang, base counts, log_ppl, the band's edges, base_failed and kept."""
    _, scored, limits = _judged(docs, band)
    limits, _ = shared.settle(limits, "bands")
    rows = scored.join(limits, F.col("lang").eqNullSafe(F.col("band_lang")), "left")
    edge = lambda side, sign: F.col("middle") + sign * band[side] * F.sqrt(F.col("spread") ** 2 + F.lit(CHAR_SD**2) / F.greatest(F.col("n_chars_scored"), F.lit(1)))
    out = rows.select(*scored.columns, edge(0, -1).alias("low"), edge(1, 1).alias("high"), base_failed().alias("base_failed"))
    inside = F.coalesce(F.col("log_ppl").between(F.col("low"), F.col("high")), F.lit(False))
    return out.withColumn("kept", ~F.col("base_failed") & inside)


def keep_good(docs: DataFrame, band: tuple[float, float] = BAND) -> DataFrame:
    """Rows of ``docs`` that quality_rules keeps, judged where their text is read, so no text is shuffled."""
    files, _, limits = _judged(docs, band)
    edges = {language(r["band_lang"]): (r["middle"], r["spread"]) for r in limits.collect()}  # a row for each language

    def run(batches):
        models = Models(files)
        for batch in steps(batches, size=_sized(files)):
            m = _measure(batch, models)
            middle, spread = np.array([edges.get(language(x), (np.nan, np.nan)) for x in batch.column("lang").to_pylist()], float).T
            width = np.sqrt(spread**2 + CHAR_SD**2 / np.maximum(m["n_chars_scored"], 1))
            good = (m["log_ppl"] >= middle - band[0] * width) & (m["log_ppl"] <= middle + band[1] * width)
            good &= (m["n_words"] >= MIN_WORDS) & (100 * m["n_repeat_words"] <= MAX_REPEAT_PERCENT * m["n_words"])
            yield batch.filter(pa.array(good))

    return docs.mapInArrow(run, docs.schema)
