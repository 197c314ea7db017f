"""The lazily split Poisson signature in numpy (for deep ladders) and with heaps (for counting work).

``sig_lp_arrow`` walks all elements of a batch down their halved level ranges at once, up to the bag's horizon; batches
give partial minima, merged by an aggregate, so a bag may be spread over any number of tasks. ``one_pass`` and
``two_phase`` visit points in ascending order with heaps and stop at the running maximum; they return the same
signature and count points, splits, draws, tracker steps and nodes held.
"""

from __future__ import annotations

import heapq
import math
import struct

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.functions.ladder import Ladder, discretize
from wsig.functions.prng import COMPONENT, FIRST, NEXT, SIDE, np_hash, np_u01

#: Expected nodes of a chunk that is walked at once; a bag's larger number is walked in parts, whose minima merge.
NODES = 1 << 18
_KEYS = ("bag", "elem", "level", "lo", "hi", "x", "j", "made_lo", "made_hi")


def _component(m: int, *keys) -> np.ndarray:
    return np.minimum((np_u01(*keys) * m).astype(np.int64), m - 1)


def wavefront(bag: np.ndarray, elem: np.ndarray, level: np.ndarray, horizon: np.ndarray, m: int, ladder: Ladder, salt: int = 0):
    """(bag, j, x, id) of all points of the elements at or under their bag's horizon; bag numbers index ``horizon``."""
    v = ladder.np_value
    top = np.full(len(elem), ladder.top, np.int64)
    zero = np.zeros(len(elem), np.int64)
    f = dict(zip(_KEYS, (bag, elem, level, zero, top, -np.log(np_u01(salt, elem, zero, top, FIRST)) / v(np.array([ladder.top]))[0], _component(m, salt, elem, zero, top, COMPONENT), zero, top)))
    keep = lambda f, mask: {k: a[mask] for k, a in f.items()}
    f = keep(f, (f["lo"] < f["level"]) & (f["x"] <= horizon[f["bag"]]))
    leaves = []
    while len(f["elem"]):
        deep = f["hi"] - f["lo"] > 1
        leaves.append(keep(f, ~deep))
        f = keep(f, deep)
        if not len(f["elem"]):
            break
        lo, hi, e = f["lo"], f["hi"], f["elem"]
        mid = lo + (hi - lo) // 2
        v_lo, v_mid, v_hi = v(lo), v(mid), v(hi)
        left = np_u01(salt, e, lo, hi, SIDE) < (v_mid - v_lo) / (v_hi - v_lo)
        owner = f | {"lo": np.where(left, lo, mid), "hi": np.where(left, mid, hi)}
        o_lo, o_hi = np.where(left, mid, lo), np.where(left, hi, mid)
        live = o_lo < f["level"]
        o = keep(f, live) | {"lo": o_lo[live], "hi": o_hi[live], "made_lo": o_lo[live], "made_hi": o_hi[live]}
        rate = np.where(left, v_hi - v_mid, v_mid - v_lo)[live]
        o["x"] = o["x"] - np.log(np_u01(salt, o["elem"], o["lo"], o["hi"], FIRST)) / rate
        o["j"] = _component(m, salt, o["elem"], o["lo"], o["hi"], COMPONENT)
        f = {k: np.concatenate([owner[k], o[k]]) for k in _KEYS}
        f = keep(f, (f["lo"] < f["level"]) & (f["x"] <= horizon[f["bag"]]))
    f = {k: np.concatenate([p[k] for p in leaves]) if leaves else np.zeros(0, np.int64) for k in _KEYS}
    out = [(f["bag"], f["j"], f["x"], np_hash(salt, f["elem"], f["made_lo"], f["made_hi"], 0).view(np.int64))]
    k = 1
    while len(f["elem"]):
        f["x"] = f["x"] - np.log(np_u01(salt, f["elem"], f["lo"], f["hi"], NEXT, k)) / (v(f["hi"]) - v(f["lo"]))
        f = keep(f, f["x"] <= horizon[f["bag"]])
        out.append((f["bag"], _component(m, salt, f["elem"], f["lo"], f["hi"], COMPONENT, k), f["x"], np_hash(salt, f["elem"], f["lo"], f["hi"], k).view(np.int64)))
        k += 1
    return tuple(np.concatenate(c) for c in zip(*out))


def _least(bag, j, x, ident, m):
    """The smallest point of each (bag, j), ties to the smaller id."""
    cell = bag * m + j
    order = np.lexsort((ident, x, cell))
    first = order[np.concatenate(([True], cell[order][1:] != cell[order][:-1]))] if len(order) else order
    return bag[first], j[first], x[first], ident[first]


def _chunks(cost: np.ndarray, most: float) -> list[tuple[int, int]]:
    """Stretches of rows whose costs sum to about ``most``, one row at least."""
    ends, out, i = np.cumsum(cost), [], 0
    while i < len(cost):
        j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0.0) + most, "right")))
        out.append((i, j))
        i = j
    return out


def _partial(rows: DataFrame, m: int, ladder: Ladder, salt: int) -> DataFrame:
    """Least points by chunk of (bag_id, elem, level, level_weight, horizon).

    An element is halved ``depth`` times at least and has level_weight * horizon points to be expected, which bounds a
    chunk's memory whatever m and the batch.
    """

    def run(batches):
        for batch in batches:
            whole = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("bag_id", "elem", "level", "level_weight", "horizon")]
            for a, b in _chunks(1.0 + ladder.depth + 2 * whole[3] * whole[4], NODES):
                bags, elem, level, _, horizons = (x[a:b] for x in whole)
                ids, bag = np.unique(bags, return_inverse=True)
                horizon = np.zeros(len(ids))
                horizon[bag] = horizons
                who, j, x, ident = _least(*wavefront(bag, elem, level, horizon, m, ladder, salt), m)
                yield pa.RecordBatch.from_arrays([pa.array(ids[who]), pa.array(j.astype(np.int32)), pa.array(x), pa.array(ident)], ["bag_id", "j", "x", "id"])

    return rows.select("bag_id", "elem", "level", "level_weight", "horizon").mapInArrow(run, "bag_id long, j int, x double, id long")


def sig_lp_arrow(bags: DataFrame, m: int, ladder: Ladder, c: float = 4.0, salt: int = 0) -> DataFrame:
    """(bag_id, j, id, h) for any ladder; bags of over a task's rows need no care, as partial minima merge."""
    from wsig.operators.poisson import until_filled

    rows = discretize(bags.select("bag_id", "elem", "weight"), ladder)
    return until_filled(rows, m, c, lambda r: _partial(r, m, ladder, salt))


# --- heaps -------------------------------------------------------------------------------------------------------------


class MaxTree:
    """The maximum of m falling values, in a tournament over pairs; an update climbs only while a maximum falls."""

    def __init__(self, m: int):
        self.m, self.steps = m, 0
        self.rows = [[math.inf] * m]
        while len(self.rows[-1]) > 1:
            self.rows.append([math.inf] * ((len(self.rows[-1]) + 1) // 2))

    @property
    def root(self) -> float:
        return self.rows[-1][0]

    def update(self, j: int, x: float) -> bool:
        """Lowers value j to x if that is lower."""
        if x >= self.rows[0][j]:
            return False
        for depth, row in enumerate(self.rows):
            if depth:
                below = self.rows[depth - 1]
                x = max(below[2 * j : 2 * j + 2])
            if x >= row[j]:
                break
            row[j] = x
            self.steps += 1
            j //= 2
        return True


class Work:
    """What an ordered walk did."""

    def __init__(self):
        self.points = self.splits = self.draws = self.peak = 0

    def as_dict(self, tracker: MaxTree) -> dict:
        return {"n_points": self.points, "n_splits": self.splits, "n_words": self.draws, "n_tree_updates": tracker.steps, "peak_nodes": self.peak}


class Signature:
    """Minima, winners and their tracker."""

    def __init__(self, m: int):
        self.m, self.tracker, self.ids, self.work = m, MaxTree(m), [None] * m, Work()

    @property
    def minima(self) -> list[float]:
        return self.tracker.rows[0]

    def offer(self, x: float, j: int, ident: tuple) -> None:
        if self.tracker.update(j, x):
            self.ids[j] = ident


class Node:
    """A level range with its current point; the point's component and identity stay with the half that keeps it."""

    __slots__ = ("x", "elem", "level", "lo", "hi", "j", "ident", "told", "number")

    def __init__(self, x, elem, level, lo, hi, j, ident):
        self.x, self.elem, self.level, self.lo, self.hi, self.j, self.ident = x, elem, level, lo, hi, j, ident
        self.told, self.number = False, 0

    def __lt__(self, other):
        return self.x < other.x

    @property
    def whole(self) -> bool:
        """All its levels are reached."""
        return self.hi <= self.level

    @property
    def partly(self) -> bool:
        return self.lo < self.level

    @property
    def single(self) -> bool:
        return self.hi - self.lo == 1


_long, _digest = struct.Struct("<q").pack, xxhash.xxh64_intdigest
#: Levels of a ladder whose values a walk keeps.
KNOWN = 1 << 16


def one_hash(h: int, *keys: int) -> int:
    """``np_hash`` of single keys, going on from the hash ``h``; without numpy's calls."""
    for k in keys:
        h = _digest(_long(k), h)
    return h


class Walker:
    """Makes, halves and advances nodes by keyed draws."""

    def __init__(self, m: int, ladder: Ladder, work: Work, salt: int = 0):
        self.m, self.ladder, self.work, self.salt = m, ladder, work, salt
        self.begun: dict[int, int] = {}  # of the bag's elements
        self.values: dict[int, float] = ladder.__dict__.setdefault("_values", {}) if ladder.top <= KNOWN else {}

    def _draw(self, elem: int, *keys: int) -> float:
        self.work.draws += 1
        h = self.begun.get(elem)
        if h is None:
            h = self.begun[elem] = one_hash(42, self.salt, elem)
        return ((one_hash(h, *keys) >> 11) + 0.5) / 2.0**53

    def _value(self, i: int) -> float:
        got = self.values.get(i)
        if got is None:
            got = float(self.ladder.np_value(np.array([i]))[0])
            if self.ladder.top <= KNOWN:
                self.values[i] = got
        return got

    def make(self, elem: int, level: int, lo: int, hi: int, after: float = 0.0) -> Node:
        self.work.points += 1
        x = after - math.log(self._draw(elem, lo, hi, FIRST)) / (self._value(hi) - self._value(lo))
        j = min(int(self._draw(elem, lo, hi, COMPONENT) * self.m), self.m - 1)
        return Node(x, elem, level, lo, hi, j, (elem, lo, hi, 0))

    def halve(self, node: Node) -> tuple[int, int]:
        """Narrows the node to the half that keeps its point and returns the other half's range."""
        self.work.splits += 1
        lo, hi = node.lo, node.hi
        mid = lo + (hi - lo) // 2
        share = (self._value(mid) - self._value(lo)) / (self._value(hi) - self._value(lo))
        if self._draw(node.elem, lo, hi, SIDE) < share:
            node.hi = mid
            return mid, hi
        node.lo = mid
        return lo, mid

    def advance(self, node: Node) -> None:
        """To a single level's next point."""
        self.work.points += 1
        node.number += 1
        k = node.number
        node.x -= math.log(self._draw(node.elem, node.lo, node.hi, NEXT, k)) / (self._value(node.hi) - self._value(node.lo))
        node.j = min(int(self._draw(node.elem, node.lo, node.hi, COMPONENT, k) * self.m), self.m - 1)
        node.ident, node.told = (node.elem, node.lo, node.hi, k), False


def _tell(node: Node, sig: Signature) -> None:
    if node.whole and not node.told:
        node.told = True
        sig.offer(node.x, node.j, node.ident)


def _descend(node: Node, heap: list, walk: Walker, sig: Signature, stop_when_whole: bool, early: bool, prune: bool) -> None:
    """Narrows a node to a single level (or to reached levels only); other halves that may matter join the heap."""
    while node.partly and not node.single and not (stop_when_whole and node.whole):
        lo, hi = walk.halve(node)
        if early or node.single:
            _tell(node, sig)
        if lo < node.level:
            other = walk.make(node.elem, node.level, lo, hi, node.x)
            if early or other.single:
                _tell(other, sig)
            if not prune or other.x <= sig.tracker.root:
                heapq.heappush(heap, other)


def _drain(heap: list, walk: Walker, sig: Signature, early: bool, prune: bool, held: int = 0) -> None:
    """Works a heap off in ascending order until its least point lies above every component."""
    while heap and heap[0].x <= sig.tracker.root:
        walk.work.peak = max(walk.work.peak, held + len(heap))
        node = heapq.heappop(heap)
        _descend(node, heap, walk, sig, False, early, prune)
        if node.partly:
            _tell(node, sig)
            walk.advance(node)
            _tell(node, sig)
            if not prune or node.x <= sig.tracker.root:
                heapq.heappush(heap, node)


def _levels(elements: list[tuple[int, float]], ladder: Ladder) -> list[tuple[int, int]]:
    return list(zip([e for e, _ in elements], ladder.np_index(np.array([w for _, w in elements], np.float64)).tolist(), strict=True)) if elements else []


def one_pass(elements: list[tuple[int, float]], m: int, ladder: Ladder, salt: int = 0, early: bool = True, prune: bool = True) -> Signature:
    """Element after element, each with a heap of its own."""
    sig = Signature(m)
    walk = Walker(m, ladder, sig.work, salt)
    for elem, level in _levels(elements, ladder):
        if level < 1:
            continue
        root = walk.make(elem, level, 0, ladder.top)
        if early or root.single:
            _tell(root, sig)
        _drain([root], walk, sig, early, prune)
    return sig


def two_phase(elements: list[tuple[int, float]], m: int, ladder: Ladder, salt: int = 0, evict: bool = True) -> Signature:
    """First each element to its smallest point that counts; then what is left of all, in one heap.

    With ``evict`` the store between the phases drops, largest first, what the falling maximum has passed.
    """
    sig = Signature(m)
    walk = Walker(m, ladder, sig.work, salt)
    store: list = []  # (-x, number, node): largest point first
    for number, (elem, level) in enumerate(_levels(elements, ladder)):
        if level < 1:
            continue
        heap = [walk.make(elem, level, 0, ladder.top)]
        _tell(heap[0], sig)
        while heap and heap[0].x <= sig.tracker.root:
            walk.work.peak = max(walk.work.peak, len(store) + len(heap))
            node = heapq.heappop(heap)
            _descend(node, heap, walk, sig, True, True, True)
            if node.whole:
                _tell(node, sig)
                heap.append(node)
                break
        for at, node in enumerate(heap):
            if node.x <= sig.tracker.root:
                heapq.heappush(store, (-node.x, number, at, node))
        while evict and store and -store[0][0] > sig.tracker.root:
            heapq.heappop(store)
    heap = [node for x, *_, node in store if -x <= sig.tracker.root]
    heapq.heapify(heap)
    _drain(heap, walk, sig, True, True)
    return sig


def in_order(bag: np.ndarray, elem: np.ndarray, weight: np.ndarray, order: str, salt: int = 0) -> np.ndarray:
    """Places of the rows bag by bag, within a bag by weight_desc, weight_asc, random (keyed) or as given."""
    if order == "random":
        return np.lexsort((np_hash(salt, 99, elem), bag))
    if order == "given":
        return np.argsort(bag, kind="stable")
    return np.lexsort((elem, weight if order == "weight_asc" else -weight, bag))


def _each_bag(bags: DataFrame, order: str, salt: int, rows_of, schema: str) -> DataFrame:
    """Rows of ``rows_of`` (bag_id, elements) for each bag, over the session's partitions: bags are small in bytes and long in work, so they must not be put together."""
    names = [c.split()[0] for c in schema.split(", ")]
    kinds = [{"long": pa.int64(), "double": pa.float64()}[c.split()[1]] for c in schema.split(", ")]

    def judge(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        bag, elem, weight = (np.concatenate([p.column(c).to_numpy(zero_copy_only=False) for p in parts]) for c in ("bag_id", "elem", "weight"))
        at = in_order(bag, elem, weight, order, salt)
        bag, elem, weight = bag[at], elem[at].tolist(), weight[at].tolist()
        cuts = [0, *(np.flatnonzero(bag[1:] != bag[:-1]) + 1).tolist(), len(bag)]
        out = [row for a, b in zip(cuts, cuts[1:]) for row in rows_of(int(bag[a]), list(zip(elem[a:b], weight[a:b], strict=True)))]
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], names)

    def run(batches):
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = batch.column("bag_id").to_numpy(zero_copy_only=False)
            if held and held[-1].column("bag_id")[-1].as_py() != keys[0]:
                yield judge(held)
                held = []
            cut = int(np.searchsorted(keys, keys[-1]))
            if cut:  # the last bag may go on in the next batch
                yield judge([*held, batch.slice(0, cut)])
                held = []
            held.append(batch.slice(cut))
        if held:
            yield judge(held)

    n = int(bags.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = bags.select("bag_id", "elem", F.col("weight").cast("double").alias("weight")).where("bag_id is not null")
    return rows.repartition(n, "bag_id").sortWithinPartitions("bag_id").mapInArrow(run, schema)


_COST = "bag_id long, n long, n_points long, n_splits long, n_words long, n_tree_updates long, peak_nodes long"


def lp_costs(bags: DataFrame, m: int, ladder: Ladder, variant: str = "two_phase", order: str = "random", **flags) -> DataFrame:
    """What a heap variant does for each bag: points, splits, draws, tracker steps, nodes held at most."""
    run = {"one_pass": one_pass, "two_phase": two_phase}[variant]

    def work(bag: int, elements: list[tuple[int, float]]) -> list[tuple]:
        sig = run(elements, m, ladder, **flags)
        return [(bag, len(elements), *sig.work.as_dict(sig.tracker).values())]

    return _each_bag(bags, order, 0, work, _COST)


def sig_lp_heap(bags: DataFrame, m: int, ladder: Ladder, variant: str = "two_phase", order: str = "random", salt: int = 0, **flags) -> DataFrame:
    """(bag_id, j, id, h) by a heap variant; a bag must fit a task."""
    run = {"one_pass": one_pass, "two_phase": two_phase}[variant]

    def winners(bag: int, elements: list[tuple[int, float]]) -> list[tuple]:
        sig = run(elements, m, ladder, salt=salt, **flags)
        return [(bag, j, int(np.uint64(one_hash(42, salt, *i)).astype(np.int64)), h) for j, (i, h) in enumerate(zip(sig.ids, sig.minima, strict=True)) if i is not None]

    long = _each_bag(bags, order, 0, winners, "bag_id long, j long, id long, h double")
    return long.select("bag_id", F.col("j").cast("int").alias("j"), "id", "h")
