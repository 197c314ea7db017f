"""Operator 6, token-id files in patched frame-of-reference blocks.

Format of a shard, little-endian: magic ``PFOR1\\n\\0\\0``, then blocks, then the index, then a footer. A block holds up to
``BLOCK`` ids: uint32 minimum, uint16 count, uint8 width, uint8 zero, uint16 exceptions, uint16 zero; the low ``width``
bits of each (id - minimum), packed from the lowest bit up; then the exceptions, as uint16 places and uint32 values
(id - minimum). The width is what the block's 90th percentile needs, or one at which the block is smaller. The index is
a uint64 for each block's byte start, a uint64 for each document's first id, with the number of ids at its end, an int64 for each
document's doc_id and a bit for each that says whether it has one. The footer holds
five uint64: blocks, documents, ids, the index's byte start and a checksum of the blocks. So an id, a block or a
document can be reached without reading what is before it.

Documents are range-sorted by doc_id (null last; equal ids by text), each task writes one shard into the folder that the
cluster shares, under a name of its own attempt, and returns its manifest row. A lost or repeated attempt leaves a file
that no manifest names. Shards follow the table's bytes, so neither a shard's index nor a task's memory grows with the table.
Tokens are those of the library, its special tokens included where a text holds one. Null and empty texts are one end id. An empty table has no shards and no rows.
"""

from __future__ import annotations

import re
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.llm import shared
from wsig.llm.textscan import Scan, steps

BLOCK, END_ID, PERCENTILE = 4096, 2, 90
MAGIC = b"PFOR1\n\0\0"
#: Bytes of text in which equal chunks are encoded once; a longer text is a step of its own.
CHUNKED = 8 << 20
_HEAD = np.dtype([("low", "<u4"), ("n", "<u2"), ("width", "u1"), ("pad", "u1"), ("exceptions", "<u2"), ("pad2", "<u2")])


def pack(values: np.ndarray, width: int) -> bytes:
    """The low ``width`` bits of each value, end to end."""
    if not width:
        return b""
    bits = np.unpackbits(np.ascontiguousarray(values, "<u4").view(np.uint8).reshape(-1, 4), axis=1, count=width, bitorder="little")
    return np.packbits(bits.reshape(-1), bitorder="little").tobytes()


def unpack(data: np.ndarray, n: int, width: int) -> np.ndarray:
    if not width:
        return np.zeros(n, np.uint32)
    bits = np.unpackbits(data, count=n * width, bitorder="little").reshape(n, width)
    wide = np.zeros((n, 32), np.uint8)
    wide[:, :width] = bits
    return np.packbits(wide, axis=1, bitorder="little").view("<u4").reshape(-1)


def encode_block(ids: np.ndarray) -> bytes:
    low = int(ids.min())
    over = (ids - np.uint32(low)).astype(np.uint32)
    widths = np.bitwise_or.reduce(over).item().bit_length()
    at = int(np.partition(over, (len(over) - 1) * PERCENTILE // 100)[(len(over) - 1) * PERCENTILE // 100]).bit_length()
    size = lambda w: len(over) * w / 8 + 6 * int((over >> np.uint32(w)).astype(bool).sum()) if w < 32 else len(over) * 4
    width = min({at, widths}, key=lambda w: (size(w), w))
    out = np.flatnonzero(over >> np.uint32(width)) if width < 32 else np.zeros(0, np.int64)
    head = np.zeros(1, _HEAD)
    head["low"], head["n"], head["width"], head["exceptions"] = low, len(ids), width, len(out)
    mask = np.uint32((1 << width) - 1)
    return head.tobytes() + pack(over & mask, width) + out.astype("<u2").tobytes() + over[out].astype("<u4").tobytes()


def decode_block(data: np.ndarray) -> np.ndarray:
    head = data[: _HEAD.itemsize].view(_HEAD)[0]
    n, width, k = int(head["n"]), int(head["width"]), int(head["exceptions"])
    a = _HEAD.itemsize
    b = a + -(-n * width // 8)
    over = unpack(data[a:b], n, width)
    places, values = data[b : b + 2 * k].view("<u2"), data[b + 2 * k : b + 6 * k]
    over[places] = np.frombuffer(values.tobytes(), "<u4")
    return over + head["low"]


class Writer:
    """Appends documents' ids to a binary stream; holds at most one block of ids and the index."""

    def __init__(self, out):
        self.out, self.rest, self.at, self.crc = out, np.zeros(0, np.uint32), len(MAGIC), 0
        self.blocks: list[int] = []
        self.firsts: list[np.ndarray] = []
        self.doc_ids: list[pa.Array] = []
        self.n = self.docs = 0
        out.write(MAGIC)

    def _block(self, ids: np.ndarray) -> None:
        data = encode_block(ids)
        self.blocks.append(self.at)
        self.at += len(data)
        self.crc = zlib.crc32(data, self.crc)
        self.out.write(data)

    def add(self, ids: np.ndarray, lengths: np.ndarray, doc_ids: pa.Array) -> None:
        self.doc_ids.append(doc_ids)
        self.firsts.append(self.n + np.cumsum(lengths) - lengths)
        self.docs += len(lengths)
        self.n += len(ids)
        ids = np.concatenate([self.rest, ids])
        whole = len(ids) // BLOCK * BLOCK
        for i in range(0, whole, BLOCK):
            self._block(ids[i : i + BLOCK])
        self.rest = ids[whole:]

    def close(self) -> None:
        if len(self.rest):
            self._block(self.rest)
        firsts = np.concatenate([*self.firsts, [self.n]]).astype("<u8")
        doc_ids = pa.chunked_array(self.doc_ids, pa.int64())
        named = np.packbits(doc_ids.is_valid().to_numpy().astype(bool), bitorder="little")
        self.out.write(np.array(self.blocks, "<u8").tobytes() + firsts.tobytes() + doc_ids.fill_null(0).to_numpy().astype("<i8").tobytes() + named.tobytes())
        self.out.write(np.array([len(self.blocks), self.docs, self.n, self.at, self.crc], "<u8").tobytes())


class Reader:
    """Reads a shard: its index, single blocks, documents."""

    def __init__(self, file):
        self.file, size = file, file.size()
        self.n_blocks, self.n_docs, self.n, self.index_at, self.crc = (int(x) for x in np.frombuffer(self._at(size - 40, 40), "<u8"))
        if self._at(0, len(MAGIC)) != MAGIC:
            raise ValueError("not a token-id shard")
        end = self.index_at + 8 * (self.n_blocks + 2 * self.n_docs + 1)
        index = np.frombuffer(self._at(self.index_at, end - self.index_at), "<u8").astype(np.int64)
        named = np.unpackbits(np.frombuffer(self._at(end, -(-self.n_docs // 8)), np.uint8), count=self.n_docs, bitorder="little").astype(bool)
        self.starts = np.append(index[: self.n_blocks], self.index_at)
        self.firsts = index[self.n_blocks : self.n_blocks + self.n_docs + 1]
        self.doc_ids = pa.array(index[self.n_blocks + self.n_docs + 1 :], mask=~named)

    def _at(self, place: int, n: int) -> bytes:
        self.file.seek(place)
        return self.file.read(n)

    def blocks(self, a: int, b: int) -> np.ndarray:
        """Ids of blocks a to b - 1."""
        data = np.frombuffer(self._at(int(self.starts[a]), int(self.starts[b] - self.starts[a])), np.uint8)
        cuts = self.starts[a : b + 1] - self.starts[a]
        return np.concatenate([decode_block(data[i:j]) for i, j in zip(cuts, cuts[1:])]) if b > a else np.zeros(0, np.uint32)

    def document(self, i: int) -> np.ndarray:
        a, b = self.firsts[i], self.firsts[i + 1]
        first = a // BLOCK
        return self.blocks(first, -(-b // BLOCK))[a - first * BLOCK : b - first * BLOCK]

    def documents(self, step: int = 256):
        """(first document, lengths, ids) for stretches of whole documents, a bounded number of blocks at a time."""
        held, doc, block = np.zeros(0, np.uint32), 0, 0
        while doc < self.n_docs:
            end = doc
            while end == doc:
                if block < self.n_blocks:
                    held = np.concatenate([held, self.blocks(block, min(block + step, self.n_blocks))])
                    block = min(block + step, self.n_blocks)
                end = int(np.searchsorted(self.firsts, self.firsts[doc] + len(held), "right")) - 1
                end = min(end, self.n_docs)
            lengths = np.diff(self.firsts[doc : end + 1])
            n = int(lengths.sum())
            yield doc, lengths, held[:n]
            held, doc = held[n:], end


class Encoder:
    """Byte-level BPE of the tokenizers library, in which equal chunks of a batch are encoded once.

    In a text whose white space is single spaces and line feeds, the pre-tokenizer always cuts before these, so encoding
    the chunks that begin with them apart gives the ids of the whole text. Chunks are found and told apart by hash in
    numpy; the different ones are encoded many at a time as one text, whose ids are cut again where a token begins with a
    space (or a line feed): no other token holds one. Other texts, and those that hold an added token, are encoded whole.
    A worker keeps its encoder.
    """

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values() if t.content]
        #: A normalizer, or an added token with white space, may reach over a chunk's edge.
        self.by_chunk = self.tokenizer.normalizer is None and not any(re.search(r"\s", t) for t in self.added)
        names = [self.tokenizer.id_to_token(i) or "" for i in range(self.tokenizer.get_vocab_size())]
        self.begins = {lead: np.array([x.startswith(sign) for x in names]) for lead, sign in ((" ", "Ġ"), ("\n", "Ċ"))}

    @classmethod
    def of(cls, path: str) -> Encoder:
        if path not in _encoders:
            _encoders[path] = cls(path)
        return _encoders[path]

    def _whole(self, texts: list[str]) -> list[np.ndarray]:
        out: list[np.ndarray] = []
        for i in range(0, len(texts), 1024):
            out += [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts[i : i + 1024], add_special_tokens=False)]
        return out

    def _together(self, chunks: list[str], lead: str) -> tuple[np.ndarray, np.ndarray]:
        """Ids end to end, and their number, of chunks that each begin with ``lead`` and hold it nowhere else."""
        ids, lengths = [], []
        for i in range(0, len(chunks), 512):
            part = chunks[i : i + 512]
            (encoded,) = self.tokenizer.encode_batch_fast(["".join(part)], add_special_tokens=False)
            got = np.array(encoded.ids, np.uint32)
            at = np.flatnonzero(self.begins[lead][got])
            if len(at) == len(part):
                ids.append(got)
                lengths.append(np.diff(np.append(at, len(got))))
            else:
                each = self._whole(part)
                ids += each
                lengths.append(np.array([len(x) for x in each], np.int64))
        return (np.concatenate(ids), np.concatenate(lengths)) if ids else (np.zeros(0, np.uint32), np.zeros(0, np.int64))

    def encode(self, column: pa.Array, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts end to end, each with its end id, and each text's number of ids."""
        scan = Scan(column)
        odd = irregular(scan) | holding(scan, self.added) if self.by_chunk else np.ones(len(scan.n_words), bool)
        keep = np.flatnonzero(~odd[scan.doc])
        doc, starts, ends = scan.doc[keep], scan.starts[keep], scan.ends[keep]
        starts = np.where(starts > scan.offsets[doc], starts - 1, starts)  # with the white space before
        marked = np.flatnonzero(_MARK[scan.bytes[ends - 1]] & _LETTER[scan.bytes[np.maximum(ends - 2, 0)]] & (ends - starts > 2))
        if len(marked):  # a comma or full stop after a letter is a chunk of its own, as the pre-tokenizer cuts there too
            at = marked + 1
            starts, doc = np.insert(starts, at, ends[marked] - 1), np.insert(doc, at, doc[marked])
            ends = np.insert(ends, at, ends[marked])
            ends[marked + np.arange(len(marked))] -= 1
        _, first, which = np.unique(scan.hash_runs(starts, ends), return_index=True, return_inverse=True)
        whole = scan.bytes.tobytes()
        lead = scan.bytes[starts[first]]
        flat, sizes = [], np.zeros(len(first), np.int64)
        places, done = np.zeros(len(first), np.int64), 0
        for sign in (" ", "\n", ""):
            mine = np.flatnonzero(lead == ord(sign)) if sign else np.flatnonzero((lead != 32) & (lead != 10))
            texts = [whole[a:b].decode() for a, b in zip(starts[first[mine]].tolist(), ends[first[mine]].tolist())]
            if sign:
                ids, n = self._together(texts, sign)
            else:
                each = self._whole(texts)
                ids, n = np.concatenate([np.zeros(0, np.uint32), *each]), np.array([len(x) for x in each], np.int64)
            flat.append(ids)
            sizes[mine], places[mine] = n, done + np.cumsum(n) - n
            done += len(ids)
        table = np.concatenate(flat)
        n = sizes[which]
        ids = table[np.arange(int(n.sum())) + np.repeat(places[which] - (np.cumsum(n) - n), n)]
        per_doc = np.bincount(doc, n, len(odd)).astype(np.int64)
        odd_at = np.flatnonzero(odd)
        texts = self._whole([whole[a:b].decode() for a, b in zip(scan.offsets[odd_at].tolist(), scan.offsets[odd_at + 1].tolist())])
        per_doc[odd_at] = [len(x) for x in texts]
        lengths = per_doc + 1
        edges = np.cumsum(lengths)
        out = np.empty(int(edges[-1]) if len(edges) else 0, np.uint32)
        out[edges - 1] = end_id
        plain = np.where(odd, 0, per_doc)
        out[np.arange(len(ids)) + np.repeat(edges - lengths - (np.cumsum(plain) - plain), plain)] = ids
        for i, x in zip(odd_at.tolist(), texts, strict=True):
            out[edges[i] - lengths[i] : edges[i] - 1] = x
        return out, lengths


_encoders: dict[str, Encoder] = {}
_PLAIN_SPACE = np.isin(np.arange(256), (0x20, 0x0A))
_MARK, _LETTER = np.isin(np.arange(256), (0x2C, 0x2E)), np.array([chr(i).isalpha() and i < 128 for i in range(256)])
_OTHER_SPACE = np.isin(np.arange(256), (0x09, 0x0B, 0x0C, 0x0D, 0x1C, 0x1D, 0x1E, 0x1F))
# UTF-8 beginnings of white space past ASCII (and of some other characters, which does no harm).
_WIDE_SPACE = (b"\xc2\x85", b"\xc2\xa0", b"\xe1\x9a\x80", b"\xe2\x80\xa8", b"\xe2\x80\xa9", b"\xe2\x80\xaf", b"\xe2\x81\x9f", b"\xe3\x80\x80", *(b"\xe2\x80" + bytes([x]) for x in range(0x80, 0x8B)))


def irregular(scan: Scan) -> np.ndarray:
    """Documents with white space that isn't a single space or line feed before a word of theirs."""
    text, offsets = scan.bytes, scan.offsets
    odd = _OTHER_SPACE[text]
    space = _PLAIN_SPACE[text]
    odd[:-1] |= space[:-1] & space[1:]  # two on end; across documents this errs to the safe side
    lasts = offsets[1:][offsets[1:] > offsets[:-1]] - 1
    odd[lasts] |= space[lasts]
    if (text >= 0xC2).any():
        whole = text.tobytes()
        seen = {x: bool((text == x).any()) for x in {m[0] for m in _WIDE_SPACE}}
        for mark in (m for m in _WIDE_SPACE if seen[m[0]]):
            at = whole.find(mark)
            while at >= 0:
                odd[at] = True
                at = whole.find(mark, at + 1)
    return scan.per_doc(odd) > 0


def holding(scan: Scan, marks: list[str]) -> np.ndarray:
    """Documents that hold one of the strings."""
    out, whole = np.zeros(len(scan.n_words), bool), scan.bytes.tobytes()
    for mark in (m.encode() for m in marks):
        at = whole.find(mark)
        while at >= 0:
            doc = int(np.searchsorted(scan.offsets, at, "right")) - 1
            out[doc] = True
            at = whole.find(mark, at + 1)
    return out


def _open(path: str, write: bool):
    from pyarrow import fs

    store, inside = fs.FileSystem.from_uri(path)
    if write:
        store.create_dir(inside.rpartition("/")[0], recursive=True)
        return store.open_output_stream(inside)
    return store.open_input_file(inside)


_MANIFEST = "shard long, path string, n_docs long, n_ids long"


def shards(docs: DataFrame) -> int:
    """As many as the scan has splits, which follow the table's bytes, and not fewer than the session's shuffle partitions."""
    return max(shared.slots(docs.sparkSession), docs.select("doc_id").rdd.getNumPartitions())


def write_shards(docs: DataFrame, tokenizer_path: str, folder: str, end_id: int = END_ID) -> DataFrame:
    """Encodes and writes; returns the manifest: shards in doc_id order with their paths, counts and packed doc_ids."""
    spark = docs.sparkSession

    def run(batches):
        from pyspark import TaskContext

        encoder, writer, path = None, None, ""
        for batch in steps(batches, size=CHUNKED):
            if encoder is None:
                encoder = Encoder.of(tokenizer_path)
                path = f"{folder}/part-{uuid.uuid4().hex}.pfor"
                sink = _open(path, True)
                writer = Writer(sink)
            writer.add(*encoder.encode(batch.column("text"), end_id), batch.column("doc_id"))
        if writer is not None:
            writer.close()
            sink.close()
            row = [TaskContext.get().partitionId(), path, writer.docs, writer.n]
            yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(row, (pa.int64(), pa.string(), pa.int64(), pa.int64()))], ["shard", "path", "n_docs", "n_ids"])

    order = [F.asc_nulls_last("doc_id"), F.xxhash64("text")]
    rows = docs.select(F.col("doc_id").cast("long"), "text").repartitionByRange(shards(docs), *order).sortWithinPartitions(*order)
    manifest, _ = shared.settle(rows.mapInArrow(run, _MANIFEST), "token-manifest")
    return manifest


def read_shards(manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 for each document, from the shards' files."""
    spark = manifest.sparkSession
    counts = sorted(manifest.select("shard", "n_ids").collect())  # a row a shard
    bases, total = [], 0
    for r in counts:
        bases.append((r["shard"], total))
        total += r["n_ids"]
    offsets = F.broadcast(spark.createDataFrame(bases, "shard long, base long"))

    def run(batches):
        for batch in batches:
            for path, base in zip(batch.column("path").to_pylist(), batch.column("base").to_pylist(), strict=True):
                with _open(path, False) as file:
                    reader = Reader(file)
                    for first, lengths, ids in reader.documents():
                        data, cuts = np.ascontiguousarray(ids, "<u4"), np.cumsum(lengths) - lengths
                        crc = [zlib.crc32(data[a : a + n]) for a, n in zip(cuts, lengths)]
                        start = base + reader.firsts[first : first + len(lengths)]
                        yield pa.RecordBatch.from_arrays([reader.doc_ids[first : first + len(lengths)], pa.array(start), pa.array(lengths), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    n = max(1, min(len(counts), shared.slots(spark)))
    return manifest.join(offsets, "shard").repartition(n).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_files(docs: DataFrame, tokenizer_path: str, folder: str | None = None) -> DataFrame:
    """Writes ``docs`` as token-id shards and returns what reading them back gives."""
    return read_shards(write_shards(docs, tokenizer_path, folder or shared.new_path(docs.sparkSession, "tokens")))
