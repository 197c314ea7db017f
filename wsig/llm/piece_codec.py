"""Operator 9, SentencePiece encoding with seeded merge-dropout, and lossless decoding.

A BPE piece model merges, again and again, the adjacent pair whose piece has the best score, leftmost first. With
dropout, a candidate merge that comes up is skipped if a hash keyed by seed, document, place in the text and piece falls
below ``alpha``; so a word is segmented in many ways, differently at each of its occurrences, and the same way on every run.

A text is cut where no piece of the model holds the two characters side by side; no merge crosses a cut, so the chunks
between are merged apart. A chunk that occurs again in a step is merged without dropout once. Where the hash skips none
of those merges, that result stands; every other occurrence goes through the agenda by its own hashes. Chunks are merged
together in numpy, a round for each merge; those of over ``WIDE`` characters by a heap of their own, in n log n steps.

Characters that the model lacks, and a literal U+2581, become byte pieces, so decoding gives every text back exactly.
Null and empty texts have no pieces (a null decodes to the empty text). Null ids take part as id 0; rows of one id and
one text are segmented alike unless a column that tells copies apart is named. An empty table gives an empty result;
other columns are ignored.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.llm.textscan import as_bytes, mix, run_hash, run_sums, steps

WIDE, ALPHA, SEED = 48, 0.1, 17
#: Bytes of text of a step, chunks merged at a time and characters of one matrix: bounds of a worker's memory.
STEP, TOGETHER, CELLS = 1 << 20, 1 << 14, 1 << 19
MARK = "▁"
_NONE = np.int32(1 << 30)
_SHIFT = 21  # bits of a symbol: pieces and all other characters
_ALL = (1 << 64) - 1


def text_key(seed: int, doc: np.ndarray, copy: np.ndarray | None = None) -> np.ndarray:
    """64 bits for each text, to which a candidate's place and piece are added."""
    key = mix(np.asarray(doc, np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed & _ALL))
    return key if copy is None else mix(key + np.asarray(copy, np.uint64))


def hashes(key, place, piece) -> np.ndarray:
    """64 bits for each candidate merge."""
    return mix(np.asarray(key, np.uint64) + ((np.asarray(place, np.uint64) << np.uint64(_SHIFT)) | np.asarray(piece, np.uint64)))


def one_hash(key: int, place: int, piece: int) -> int:
    """The same of one candidate, in Python's integers."""
    x = (key + (place << _SHIFT | piece)) & _ALL
    x = ((x ^ x >> 30) * 0xBF58476D1CE4E5B9) & _ALL
    x = ((x ^ x >> 27) * 0x94D049BB133111EB) & _ALL
    return x ^ x >> 31


def _limit(alpha: float) -> int:
    """Hashes under this are skipped: all but one in 2**64 when alpha is 1."""
    return min(int(alpha * 2**64), _ALL)


def _ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The places starts[i], starts[i] + 1, ... of stretches, end to end."""
    before = np.cumsum(lengths) - lengths
    return np.arange(int(lengths.sum())) + np.repeat(starts - before, lengths)


class Pieces:
    """A SentencePiece BPE model's pieces, scores and merges."""

    def __init__(self, path: str):
        from sentencepiece import SentencePieceProcessor

        model = SentencePieceProcessor(model_file=path)
        n = model.get_piece_size()
        names = [model.id_to_piece(i) for i in range(n)]
        self.byte_ids = np.zeros(256, np.int32)
        plain: dict[str, int] = {}
        texts = [b""] * n
        for i, name in enumerate(names):
            if model.is_byte(i):
                self.byte_ids[int(name[3:5], 16)] = i
                texts[i] = bytes([int(name[3:5], 16)])
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
                plain[name.replace(MARK, " ")] = i
                texts[i] = name.replace(MARK, " ").encode()
        self.plain = plain
        order = sorted(plain.values(), key=lambda i: (-model.get_score(i), i))
        self.rank = np.full(n, _NONE, np.int32)
        self.rank[order] = np.arange(len(order))
        self.pairs = {}
        beside = set()
        for text, i in plain.items():
            beside.update(zip(text, text[1:]))
            for cut in range(1, len(text)):
                a, b = plain.get(text[:cut]), plain.get(text[cut:])
                if a is not None and b is not None:
                    self.pairs[a << _SHIFT | b] = i
        self._slots()
        letters = sorted({c for pair in beside for c in pair})
        self.letter = np.zeros(0x110000, np.uint16)
        self.letter[[ord(c) for c in letters]] = np.arange(1, len(letters) + 1)
        self.beside = np.zeros((len(letters) + 1, len(letters) + 1), bool)
        for a, b in beside:
            self.beside[self.letter[ord(a)], self.letter[ord(b)]] = True
        self.n = n
        self.lengths = np.array([len(t) for t in texts])
        self.table = np.frombuffer(b"".join(texts), np.uint8)
        self.places = np.cumsum(self.lengths) - self.lengths
        self.symbols = np.full(0x110000, -1, np.int32)
        self.strange: list[bytes] = []

    def symbol(self, c: str) -> int:
        """A character's piece; its byte piece; or a number above the pieces, for several byte pieces."""
        known = int(self.symbols[ord(c)])
        if known < 0:
            raw = c.encode()
            known = self.plain.get(c, -1) if c != MARK else -1
            if known < 0 and len(raw) == 1:
                known = int(self.byte_ids[raw[0]])
            if known < 0:
                known = self.n + len(self.strange)
                self.strange.append(raw)
            self.symbols[ord(c)] = known
        return known

    def symbols_of(self, points: np.ndarray) -> np.ndarray:
        out = self.symbols[points]
        new = np.unique(points[out < 0])
        if len(new):
            for c in new.tolist():
                self.symbol(chr(c))
            out = self.symbols[points]
        return out

    def spelled(self, symbols: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Piece ids of symbols, the strange ones as their bytes' pieces, and the new number for each stretch."""
        odd = symbols >= self.n
        if not odd.any():
            return symbols, counts
        spelling = [self.byte_ids[list(raw)] for raw in self.strange]
        width = np.ones(len(symbols), np.int64)
        width[odd] = np.array([len(x) for x in spelling])[symbols[odd] - self.n]
        out = np.repeat(symbols, width)
        out[np.repeat(odd, width)] = np.concatenate([spelling[k] for k in (symbols[odd] - self.n).tolist()])
        edges = np.concatenate(([0], np.cumsum(width)))[np.concatenate(([0], np.cumsum(counts)))]
        return out, np.diff(edges)

    def _slots(self) -> None:
        """The pairs in an open-addressed table of 4 to 8 slots each, so that most are found at the first look."""
        keys, ids = np.array(list(self.pairs), np.int64), np.array(list(self.pairs.values()), np.int32)
        self.bits = max(4, 2 + len(keys).bit_length())
        self.slot_keys, self.slot_ids = np.full(1 << self.bits, -1, np.int64), np.full(1 << self.bits, -1, np.int32)
        at = self._slot(keys)
        while len(keys):
            free = np.flatnonzero(self.slot_keys[at] < 0)
            _, one = np.unique(at[free], return_index=True)
            put = free[one]
            self.slot_keys[at[put]], self.slot_ids[at[put]] = keys[put], ids[put]
            left = np.ones(len(keys), bool)
            left[put] = False
            keys, ids, at = keys[left], ids[left], (at[left] + 1) & ((1 << self.bits) - 1)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def join(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The piece that two symbols merge to, or -1."""
        key = (left.astype(np.int64) << _SHIFT) | right
        at = self._slot(key)
        got = self.slot_keys[at]
        out = np.where(got == key, self.slot_ids[at], -1)
        more = np.flatnonzero((got != key) & (got >= 0))
        while len(more):
            at[more] = (at[more] + 1) & ((1 << self.bits) - 1)
            got = self.slot_keys[at[more]]
            hit = got == key[more]
            out[more[hit]] = self.slot_ids[at[more[hit]]]
            more = more[~hit & (got >= 0)]
        return out

    def cuts(self, points: np.ndarray) -> np.ndarray:
        """Whether a character can't share a piece with the one before it."""
        out = np.ones(len(points), bool)
        letter = self.letter[points]
        out[1:] = ~self.beside[letter[:-1], letter[1:]]
        return out

    def agenda(self, symbols: list[int], key: int = 0, place: int = 0, limit: int = 0) -> tuple[list[int], list[tuple[int, int]]]:
        """One chunk's symbols after all merges by a heap of candidates, and the merges made (place in the chunk, piece)."""
        symbols = list(symbols)
        n = len(symbols)
        after, before, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
        heap: list[tuple[int, int, int, int]] = []
        made = []

        def offer(i):
            j = after[i]
            if i >= 0 and j < n:
                piece = self.pairs.get(symbols[i] << _SHIFT | symbols[j])
                if piece is not None:
                    heapq.heappush(heap, (int(self.rank[piece]), i, symbols[i] << _SHIFT | symbols[j], piece))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, i, pair, piece = heapq.heappop(heap)
            j = after[i]
            if not alive[i] or j >= n or symbols[i] << _SHIFT | symbols[j] != pair:
                continue
            if limit and one_hash(key, place + i, piece) < limit:
                continue
            made.append((i, piece))
            symbols[i], alive[j] = piece, False
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            if before[i] >= 0:
                offer(before[i])
            offer(i)
        return [s for s, a in zip(symbols, alive, strict=True) if a], made

    def _rounds(self, syms: np.ndarray, size: np.ndarray, key: np.ndarray | None, start: np.ndarray | None, limit: int, note) -> np.ndarray:
        """Chunks of nearly one width, a row each: a round makes the best merge of every chunk, in place.

        Returns which characters' cells still hold a symbol; note(rows, places, pieces) takes the merges.
        """
        n, width = syms.shape
        column, bound = np.arange(width), np.uint64(limit)
        alive = column < size[:, None]
        if width < 2:
            return alive
        cells = syms.reshape(-1)  # a cell is row * width + place
        after = np.broadcast_to(np.arange(1, width + 1, dtype=np.int32), syms.shape).copy().reshape(-1)
        before = np.broadcast_to(np.arange(-1, width - 1, dtype=np.int32), syms.shape).copy().reshape(-1)
        rank, made = np.full((n, width), _NONE, np.int32), np.zeros((n, width), np.int32)
        ranks, mades, living = rank.reshape(-1), made.reshape(-1), alive.reshape(-1)

        def judge(rows, places, nexts):
            """Rates the pairs that begin at the places; nexts are where their right halves are."""
            here = rows * width + places
            piece = self.join(cells[here], cells[rows * width + nexts])
            some = np.flatnonzero(piece >= 0)
            if limit and len(some):
                r = rows[some]
                some = some[hashes(key[r], start[r] + places[some], piece[some]) >= bound]
            ranks[here] = _NONE
            ranks[here[some]], mades[here[some]] = self.rank[piece[some]], piece[some]

        rows, places = np.nonzero(column[None, :-1] + 1 < size[:, None])
        judge(rows, places, places + 1)
        live = np.arange(n)
        while len(live):
            now = rank if len(live) == n else rank[live]
            best = now.argmin(axis=1)
            going = now[np.arange(len(live)), best] < _NONE
            live, best = live[going], best[going]
            at = live * width + best
            if note is not None and len(live):
                note(live, best, mades[at])
            cells[at] = mades[at]
            gone = live * width + after[at]
            living[gone], ranks[gone] = False, _NONE
            follows = after[gone]
            after[at] = follows
            some = follows < size[live]
            before[live[some] * width + follows[some]] = best[some]
            ranks[at] = _NONE
            judge(live[some], best[some], follows[some])
            ahead = before[at]
            some = ahead >= 0
            judge(live[some], ahead[some], best[some])
        return alive

    def merged(self, symbols: np.ndarray, starts: np.ndarray, lengths: np.ndarray, key: np.ndarray | None = None, place: np.ndarray | None = None, limit: int = 0):
        """Symbols and their number of each chunk after its merges, and the merges (chunk, place, piece) by chunk where nothing is skipped.

        Chunk i is symbols[starts[i] : starts[i] + lengths[i]]; ``key`` and ``place`` are its text's key and its place there.
        """
        flat, counts = np.zeros(int(lengths.sum()), np.int32), np.zeros(len(lengths), np.int64)
        room = np.cumsum(lengths) - lengths
        noted: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        order = np.argsort(lengths, kind="stable")
        wide = int(np.searchsorted(lengths[order], WIDE, "right"))
        i = 0
        while i < wide:
            j = min(wide, i + TOGETHER)
            j = max(i + 1, min(j, i + CELLS // int(lengths[order[j - 1]])))
            mine = order[i:j]
            width = int(lengths[mine[-1]])
            at = starts[mine][:, None] + np.arange(width)
            inside = np.arange(width) < lengths[mine][:, None]
            syms = np.where(inside, symbols[np.minimum(at, len(symbols) - 1)], 0)

            def note(rows, places, pieces, mine=mine):
                noted.append((mine[rows], places, pieces))

            alive = self._rounds(syms, lengths[mine], None if key is None else key[mine], None if place is None else place[mine], limit, None if limit else note)
            counts[mine] = alive.sum(axis=1)
            flat[_ragged(room[mine], counts[mine])] = syms[alive]
            i = j
        for k in order[wide:].tolist():
            out, made = self.agenda(symbols[starts[k] : starts[k] + lengths[k]].tolist(), int(key[k]) if limit else 0, int(place[k]) if limit else 0, limit)
            counts[k] = len(out)
            flat[room[k] : room[k] + len(out)] = out
            if made and not limit:
                noted.append((np.full(len(made), k), np.array([p for p, _ in made]), np.array([p for _, p in made])))
        flat = flat[_ragged(room, counts)]
        if limit:
            return flat, counts, None
        chunk, at, piece = (np.concatenate(x) for x in zip(*noted)) if noted else (np.zeros(0, np.int64),) * 3
        by = np.argsort(chunk, kind="stable")
        return flat, counts, (chunk[by], at[by], piece[by])


class Codec:
    """Encodes and decodes batches of texts. A worker keeps its codec for its next task."""

    _made: dict[tuple, Codec] = {}

    def __init__(self, path: str, alpha: float = ALPHA, seed: int = SEED):
        self.pieces, self.alpha, self.seed = Pieces(path), alpha, seed

    @classmethod
    def of(cls, path: str, alpha: float, seed: int = SEED) -> Codec:
        if (path, alpha, seed) not in cls._made:
            cls._made[path, alpha, seed] = cls(path, alpha, seed)
        return cls._made[path, alpha, seed]

    def encode(self, data: np.ndarray, offsets: np.ndarray, ids: np.ndarray, copies: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Piece ids of all texts end to end and each text's number of them, from UTF-8 bytes end to end and their offsets."""
        p = self.pieces
        whole = np.frombuffer(data.tobytes().decode("utf-8").encode("utf-32-le"), np.uint32)
        leads = np.concatenate(([0], np.cumsum((data & 0xC0) != 0x80)))
        n_chars = np.diff(leads[offsets])
        some = np.flatnonzero(n_chars)
        size = np.where(n_chars > 0, n_chars + 1, 0)  # with the space that encoding puts before each text
        text_at = np.cumsum(size) - size
        points = np.full(int(size.sum()), 0x20, np.uint32)
        body = np.ones(len(points), bool)
        body[text_at[some]] = False
        points[body] = whole
        cut = p.cuts(points)
        cut[text_at[some]] = True
        starts = np.flatnonzero(cut)
        lengths = np.diff(np.append(starts, len(points)))
        text = np.searchsorted(text_at[some], starts, "right") - 1
        symbols = p.symbols_of(points)
        sums = run_sums(points.astype(np.uint64) + np.uint64(1), 0)
        _, first, which = np.unique(run_hash(sums, starts, starts + lengths, 0), return_index=True, return_inverse=True)
        del sums, whole, leads
        out, counts, merges = p.merged(symbols, starts[first], lengths[first])
        source, limit = which, _limit(self.alpha)
        if limit:
            chunk, place, piece = merges
            n_merges = np.bincount(chunk, minlength=len(first))
            merge_at = np.cumsum(n_merges) - n_merges
            keys = text_key(self.seed, ids[some], None if copies is None else copies[some])
            in_text = starts - text_at[some][text]
            hit = []
            for i in range(0, len(starts), 1 << 17):  # occurrences at a time
                n = n_merges[which[i : i + (1 << 17)]]
                at = _ragged(merge_at[which[i : i + (1 << 17)]], n)
                who = np.repeat(np.arange(i, i + len(n)), n)
                below = hashes(keys[text[who]], in_text[who] + place[at], piece[at]) < np.uint64(limit)
                hit.append(np.unique(who[below]))
            hit = np.concatenate(hit) if hit else np.zeros(0, np.int64)
            own, n_own, _ = p.merged(symbols, starts[hit], lengths[hit], keys[text[hit]], in_text[hit], limit)
            source = which.copy()
            source[hit] = len(counts) + np.arange(len(hit))
            out, counts = np.concatenate([out, own]), np.concatenate([counts, n_own])
        n = counts[source]
        found = out[_ragged((np.cumsum(counts) - counts)[source], n)]
        per_text = np.zeros(len(offsets) - 1, np.int64)
        per_text[some] = np.bincount(text, n, len(some)).astype(np.int64)
        return p.spelled(found, per_text)

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of all texts end to end and each text's length, from all ids and each text's number of ids."""
        p = self.pieces
        lengths = p.lengths[ids]
        text = p.table[_ragged(p.places[ids], lengths)]
        edges = np.concatenate(([0], np.cumsum(lengths)))[np.concatenate(([0], np.cumsum(counts))).astype(np.int64)]
        some = counts > 0
        keep = np.ones(len(text), bool)
        keep[edges[:-1][some]] = False  # the space that encoding puts before each text
        return text[keep], np.diff(edges) - some


def encode_pieces(docs: DataFrame, model_path: str, alpha: float = ALPHA, seed: int = SEED, copy: str | None = None) -> DataFrame:
    """doc_id, n_pieces, pieces (ids) and lossless (whether decoding gave the text back) for each row of ``docs``.

    ``copy`` names an integer column by which copies of a document are segmented differently.
    """

    def run(batches):
        codec = None
        for batch in steps(batches, size=STEP):
            codec = codec or Codec.of(model_path, alpha, seed)
            number = lambda c: batch.column(c).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)  # noqa: E731, B023
            want, offsets = as_bytes(batch.column("text"))
            ids, counts = codec.encode(want, offsets, number("doc_id"), None if copy is None else number("copy"))
            back, lengths = codec.decode(ids, counts)
            if len(back) == len(want) and (lengths == np.diff(offsets)).all():
                same = np.diff(np.concatenate(([0], np.cumsum(back != want)))[offsets]) == 0
            else:
                at = np.concatenate(([0], np.cumsum(lengths)))
                same = np.array([back[a:b].tobytes() == want[c:d].tobytes() for a, b, c, d in zip(at, at[1:], offsets, offsets[1:])])
            edges = pa.array(np.concatenate(([0], np.cumsum(counts))).astype(np.int32))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(counts), pa.ListArray.from_arrays(edges, pa.array(ids.astype(np.int32))), pa.array(same)], ["doc_id", "n_pieces", "pieces", "lossless"])

    columns = [F.col("doc_id").cast("long"), "text"] + ([F.col(copy).cast("long").alias("copy")] if copy else [])
    return docs.select(*columns).mapInArrow(run, "doc_id long, n_pieces long, pieces array<int>, lossless boolean")


def decode_pieces(encoded: DataFrame, model_path: str) -> DataFrame:
    """doc_id and text from doc_id and pieces."""

    def run(batches):
        codec = None
        for batch in batches:
            codec = codec or Codec.of(model_path, 0.0)
            lists = batch.column("pieces")
            lists = lists.fill_null([]) if lists.null_count else lists
            counts = np.diff(lists.offsets.to_numpy())
            back, lengths = codec.decode(lists.flatten().to_numpy(zero_copy_only=False), counts)
            edges = np.concatenate(([0], np.cumsum(lengths))).astype(np.int64)
            whole = back.tobytes()
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([whole[a:b].decode() for a, b in zip(edges, edges[1:])], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "pieces").mapInArrow(run, "doc_id long, text string")
