"""Mergeable summaries: zero, fold of an Arrow batch, merge of disjoint inputs, and a finishing step."""

from __future__ import annotations

import math
import pickle
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import types as T

from .functions.order_code import OrderCode


class Summary:
    result_schema = ""
    # rows that a fold likes to get at once, 0 for batches as they come
    batch_rows = 0

    def zero(self):
        raise NotImplementedError

    def fold(self, state, batch: pa.RecordBatch):
        raise NotImplementedError

    def merge(self, a, b):
        raise NotImplementedError

    def finalize(self, state) -> pa.Table:
        raise NotImplementedError

    def dump(self, state) -> bytes:
        return pickle.dumps(state, protocol=5)

    def load(self, data: bytes):
        return pickle.loads(data)


class ReduceSummary(Summary):
    """Same-type reduce: state is a value or None."""

    def __init__(self, f: Callable, finish: Callable, result_schema: str):
        self.f, self.finish, self.result_schema = f, finish, result_schema

    def zero(self):
        return None

    def fold(self, state, batch):
        for v in batch.column(0).to_pylist():
            if v is not None:
                state = v if state is None else self.f(state, v)
        return state

    def merge(self, a, b):
        return b if a is None else a if b is None else self.f(a, b)

    def finalize(self, state):
        return self.finish(state)


class TaggedSummary(Summary):
    """Finishes inside a merge, found by counting rows: ("open", rows, state) or ("finished", rows, answer)."""

    def __init__(self, inner: Summary, total: int):
        self.inner, self.total = inner, total

    def zero(self):
        return ("open", 0, self.inner.zero())

    def _tag(self, rows, state):
        return ("finished", rows, self.inner.finalize(state)) if rows == self.total else ("open", rows, state)

    def fold(self, state, batch):
        tag, rows, own = state
        if tag == "finished":
            raise ValueError("a finished state takes no more rows")
        return self._tag(rows + batch.num_rows, self.inner.fold(own, batch))

    def merge(self, a, b):
        if not a[1] or not b[1]:
            return b if not a[1] else a
        if "finished" in (a[0], b[0]):
            raise ValueError("a finished state cannot be merged")
        return self._tag(a[1] + b[1], self.inner.merge(a[2], b[2]))


class WindowSummary(Summary):
    """Counts codes below `low` and keeps those up to `high`; finishes with the value of rank `k`."""

    def __init__(self, low, high, k: int, kind: T.DataType):
        self.code, self.k = OrderCode(kind), k
        self.low, self.high = low, high
        self.result_schema = T.StructType([T.StructField("value", kind)])

    def zero(self):
        return 0, []

    def fold(self, state, batch):
        x = self.code.encode(batch.column(0))
        inside = x[(x >= self.low) & (x <= self.high)]
        return state[0] + int((x < self.low).sum()), [*state[1], inside] if len(inside) else state[1]

    def merge(self, a, b):
        return a[0] + b[0], a[1] + b[1]

    def finalize(self, state):
        at = self.k - state[0] - 1
        return pa.table({"value": self.code.decode(np.sort(np.concatenate(state[1]))[at : at + 1])})


class CountMin(Summary):
    """Rows of counters at hashed places; the batch's columns are one place for each row. Finishes as rows, zeros too."""

    result_schema = "row int, place int, count long, total long"

    def __init__(self, width: int, depth: int):
        self.width, self.depth = width, depth

    def zero(self):
        return np.zeros((self.depth, self.width), np.int64)

    def fold(self, state, batch):
        for i in range(self.depth):
            state[i] += np.bincount(batch.column(i).to_numpy(), minlength=self.width)
        return state

    def merge(self, a, b):
        return a + b

    def finalize(self, state):
        row, place = (x.ravel().astype(np.int32) for x in np.indices(state.shape))
        return pa.table({"row": row, "place": place, "count": state.ravel(), "total": np.full(state.size, state[0].sum())})


class GKSummary(Summary):
    """Rank sketch over order codes: values with rank gains `g` and slack `delta`, g + delta <= 2 * eps * n; n is kept beside.

    Rows wait in a head that is sorted and compressed when full. `head` is its size: a number of rows, "proportional" (`factor`
    times the tuples held, which restores the classical time), or "classical", where rows enter one at a time.
    Finishes with q, n, value and values `low`, `high` that are sure to enclose the rank.
    """

    def __init__(self, qs: list[float], eps: float, kind: T.DataType, head: int | str = 50_000, factor: float = 8.0):
        if any(not 0 <= q <= 1 for q in qs):
            raise ValueError("q must lie between 0 and 1")
        self.qs, self.eps, self.head, self.factor, self.code = qs, eps, head, factor, OrderCode(kind)
        self.result_schema = T.StructType([T.StructField("q", T.DoubleType()), T.StructField("n", T.LongType()), *[T.StructField(c, kind) for c in ("value", "low", "high")]])

    def zero(self):
        return None

    def _capacity(self, tuples: int) -> int:
        return max(1000, int(self.factor * tuples)) if self.head == "proportional" else int(self.head)

    def fold(self, state, batch):
        x = self.code.sortable(batch.column(0))
        if not len(x):
            return state
        if self.head == "classical":
            return self._insert(state, self.code.codes(x))
        sketch, waiting = (None, []) if state is None else (state[:4] if state[0] is not None else None, state[4])
        waiting = [*waiting, x]
        if sum(map(len, waiting)) >= self._capacity(len(sketch[0]) if sketch else 0):
            sketch, waiting = self._flushed(sketch, waiting), []
        return (*(sketch or (None, None, None, 0)), waiting)

    def _flushed(self, sketch, waiting):
        own = self._own(np.sort(np.concatenate(waiting)))
        return own if sketch is None else self._compress(self._union(sketch, own))

    def _own(self, v):
        """What `_compress` makes of sorted rows, each a tuple of its own: every so many rows one is kept, and the first and last."""
        n, room = len(v), int(2 * self.eps * len(v))
        if n < 3 or room < 2:
            return self.code.codes(v), np.ones(n, np.int64), np.zeros(n, np.int64), n
        keep = np.array([n - 1, *range(n - 2, 0, -room), 0])[::-1]
        return self.code.codes(v[keep]), np.diff(keep, prepend=-1), np.zeros(len(keep), np.int64), n

    def settled(self, state):
        """(values, g, delta, n) with an empty head."""
        if state is None or not state[4]:
            return state and state[:4]
        return self._flushed(state[:4] if state[0] is not None else None, state[4])

    def dump(self, state):
        s = self.settled(state)
        return pickle.dumps(s and (*s, []), protocol=5)

    def _insert(self, state, x):
        """The classical form: a row takes its place with the slack allowed there, compressed every 1 / (2 * eps) rows."""
        v, g, d, n, _ = state or ([], [], [], 0, [])
        v, g, d = list(v), list(g), list(d)
        every = max(1, int(1 / (2 * self.eps)))
        from bisect import bisect_right

        for value in x.tolist():
            at = bisect_right(v, value)
            slack = 0 if at in (0, len(v)) else max(0, int(2 * self.eps * n) - 1)
            v.insert(at, value)
            g.insert(at, 1)
            d.insert(at, slack)
            n += 1
            if n % every == 0:
                cv, cg, cd, _ = self._compress((self._values(v), np.array(g, np.int64), np.array(d, np.int64), n))
                v, g, d = cv.tolist(), cg.tolist(), cd.tolist()
        return self._values(v), np.array(g, np.int64), np.array(d, np.int64), n, []

    def _values(self, v: list) -> np.ndarray:
        if self.code.plain:
            return np.array(v, np.int64)
        out = np.empty(len(v), object)
        out[:] = v
        return out

    def merge(self, a, b):
        a, b = self.settled(a), self.settled(b)
        if a is None or b is None:
            one = b if a is None else a
            return one and (*one, [])
        return (*self._compress(self._union(a, b)), [])

    @staticmethod
    def _union(a, b):
        def widened(own, other, side):
            # the next larger value of the other sketch bounds how far a rank may move
            nxt = np.searchsorted(other[0], own[0], side=side)
            slack = np.append(other[1] + other[2] - 1, 0)
            return own[2] + slack[nxt]

        v = np.concatenate([a[0], b[0]])
        g = np.concatenate([a[1], b[1]])
        d = np.concatenate([widened(a, b, "left"), widened(b, a, "right")])
        order = np.argsort(v, kind="stable")
        return v[order], g[order], d[order], a[3] + b[3]

    def _compress(self, s):
        v, g, d, n = s
        room = int(2 * self.eps * n)
        if len(v) < 3 or room < 2:
            return s
        upto = np.cumsum(g)
        # a kept tuple i takes in the neighbours to its left whose ranks still fit; the next one kept stands before them
        before = np.clip(np.searchsorted(upto, upto + d - room), 0, np.arange(-1, len(v) - 1))
        keep, i = [len(v) - 1], len(v) - 2
        while i >= 1:
            keep.append(i)
            i = before.item(i)
        keep = np.array([*keep, 0])[::-1]
        gains = np.diff(upto[keep], prepend=0)
        return v[keep], gains, d[keep], n

    def value_at(self, s, k: int):
        v, g, d, n = s
        if k <= 1 or k >= n:
            return v[0] if k <= 1 else v[-1]
        low = np.cumsum(g)
        return v[int(np.argmin(np.maximum(k - low, low + d - k)))]

    def quantile(self, state, q: float):
        """The code of the q-quantile."""
        s = self.settled(state)
        return self.value_at(s, rank_of(q, s[3]))

    def finalize(self, state):
        s = self.settled(state)
        if s is None:
            return self.result_schema_table()
        slack = 2 * math.ceil(self.eps * s[3]) + 1
        ranks = [rank_of(q, s[3]) for q in self.qs]
        columns = [self.code.decode(self._values([self.value_at(s, k + move) for k in ranks])) for move in (0, -slack, slack)]
        return pa.table([pa.array([float(q) for q in self.qs]), pa.array([s[3]] * len(ranks), pa.int64()), *columns], names=["q", "n", "value", "low", "high"])

    def result_schema_table(self):
        empty = self.code.decode(self._values([]))
        return pa.table([pa.array([], pa.float64()), pa.array([], pa.int64()), empty, empty, empty], names=["q", "n", "value", "low", "high"])


def rank_of(q: float, n: int) -> int:
    """Rank of the q-quantile: the ceiling of q * n in decimal, between 1 and n."""
    from decimal import ROUND_CEILING, Decimal

    return min(max(int((Decimal(str(q)) * n).to_integral_value(ROUND_CEILING)), 1), n)


class NearestValues(Summary):
    """The `m` least (or greatest) values; finishes with the farthest of them, or with all of them in order."""

    def __init__(self, m: int, least: bool, kind: T.DataType, every: bool = False, trim: bool = True):
        self.m, self.least, self.every, self.trim, self.code = m, least, every, trim, OrderCode(kind)
        self.result_schema = T.StructType([T.StructField("value", kind)])

    def zero(self):
        return None

    def fold(self, state, batch):
        x = self.code.encode(batch.column(0))
        return _nearest(x if state is None else np.concatenate([state, x]), self.m, self.least)

    def merge(self, a, b):
        x = np.concatenate([a, b])
        return _nearest(x, self.m, self.least) if self.trim else x

    def finalize(self, state):
        x = np.sort(_nearest(state, self.m, self.least))
        x = (x if self.least else x[::-1]) if self.every else x[-1:] if self.least else x[:1]
        return pa.table({"value": self.code.decode(x)})


def _nearest(x: np.ndarray, m: int, least: bool) -> np.ndarray:
    if len(x) <= m:
        return x
    if x.dtype == object:
        x = np.sort(x)
        return x[:m] if least else x[len(x) - m :]
    return np.partition(x, m - 1)[:m] if least else np.partition(x, len(x) - m)[len(x) - m :]


class NearestOfMany(Summary):
    """For each of several pivots (number, code, m, least) the `m` nearest codes beyond it; finishes with the farthest of each."""

    def __init__(self, pivots: list[tuple], kind: T.DataType, trim: bool = True):
        self.pivots, self.trim, self.code = pivots, trim, OrderCode(kind)
        self.result_schema = T.StructType([T.StructField("no", T.IntegerType()), T.StructField("value", kind)])

    def zero(self):
        return None

    def fold(self, state, batch):
        x = self.code.encode(batch.column(0))
        out = []
        for i, (_, code, m, least) in enumerate(self.pivots):
            beyond = x[x > code] if least else x[x < code]
            out.append(_nearest(beyond if state is None else np.concatenate([state[i], beyond]), m, least))
        return out

    def merge(self, a, b):
        joined = [np.concatenate(pair) for pair in zip(a, b, strict=True)]
        return [_nearest(x, m, least) for x, (_, _, m, least) in zip(joined, self.pivots, strict=True)] if self.trim else joined

    def finalize(self, state):
        found = [np.sort(_nearest(x, m, least))[-1 if least else 0] for x, (_, _, m, least) in zip(state, self.pivots, strict=True)]
        codes = np.array(found, np.int64 if self.code.plain else object)
        return pa.table({"no": pa.array([p[0] for p in self.pivots], pa.int32()), "value": self.code.decode(codes)})


class CounterSummary(Summary):
    """Labels with counts and errors, at most `capacity` of them between steps; `lost` is what collapses took away.

    Finishes with the k largest as ranked rows, or with `export="arrays"` as one row of two flat arrays, counts narrowed to 32 bits
    where `count_type` is "int" (refused if one does not fit) or "auto" (if all fit).
    """

    batch_rows = 1 << 19

    def __init__(self, k: int, capacity: int, kind: T.DataType, export: str = "rows", count_type: str = "auto"):
        if export not in ("rows", "arrays") or count_type not in ("int", "bigint", "auto"):
            raise ValueError("export is rows or arrays, count_type int, bigint or auto")
        self.k, self.capacity, self.code, self.export, self.count_type = k, capacity, OrderCode(kind), export, count_type
        rows = [("rank", T.IntegerType()), ("item", kind), ("estimate", T.LongType()), ("error", T.LongType()), ("guaranteed", T.BooleanType()), ("lost", T.LongType()), ("survivors", T.LongType())]
        narrow = T.IntegerType() if count_type == "int" else T.LongType()
        arrays = [("labels", T.ArrayType(kind)), ("counts", T.ArrayType(narrow)), ("bytes", T.LongType())]
        self.result_schema = T.StructType([T.StructField(*f) for f in (rows if export == "rows" else arrays)])

    def zero(self):
        return None

    @staticmethod
    def _sum(labels, *columns):
        if labels.dtype == object and len(labels):
            coded = _text(labels).dictionary_encode()
            inverse, u = coded.indices.to_numpy(zero_copy_only=False), np.empty(len(coded.dictionary), object)
            u[:] = coded.dictionary.to_pylist()
        else:
            u, inverse = np.unique(labels, return_inverse=True)
        out = [np.zeros(len(u), np.int64) for _ in columns]
        for o, c in zip(out, columns, strict=True):
            np.add.at(o, inverse, c)
        return (u, *out)

    def fold(self, state, batch):
        if batch.num_columns == 2:  # label and weight
            u, n = self._sum(self.code.encode(batch.column(0)), batch.column(1).to_numpy(zero_copy_only=False))
        else:
            met = batch.column(0).drop_null().value_counts()
            u, n = self._sum(self.code.encode(met.field("values")), met.field("counts").to_numpy(zero_copy_only=False))
        if not len(u):
            return state
        own = self.shrink(u, n.astype(np.int64), np.zeros(len(u), np.int64), 0)
        return own if state is None else self.merge(state, own)

    def whole(self, state) -> bool:
        """Whether every label met has its counter and its true count."""
        return state is None or not state[3]

    def held(self, state) -> int:
        return 0 if state is None else len(state[0])

    def counted(self, state) -> pa.Table:
        """item, count of all counters."""
        return pa.table({"item": self.code.decode(state[0]), "count": pa.array(state[1], pa.int64())})

    def finalize(self, state):
        labels, counts, errors, lost = state
        order = _largest(labels, counts, self.k + 1)
        top, rest = order[: self.k], order[self.k :]
        if self.export == "arrays":
            big = bool(len(top)) and int(counts[top].max()) >= 1 << 31
            if big and self.count_type == "int":
                raise OverflowError("a count does not fit 32 bits")
            width = 8 if big or self.count_type == "bigint" else 4
            kind = pa.int32() if self.count_type == "int" else pa.int64()
            bytes_ = self.code.decode(labels[top]).nbytes + width * len(top)
            return pa.table({"labels": pa.array([self.code.decode(labels[top])], pa.list_(self.code.arrow)), "counts": pa.array([counts[top]], pa.list_(kind)), "bytes": pa.array([bytes_], pa.int64())})
        bar = counts[rest[0]] if len(rest) else 0
        return pa.table({
            "rank": pa.array(np.arange(1, len(top) + 1), pa.int32()), "item": self.code.decode(labels[top]), "estimate": pa.array(counts[top], pa.int64()), "error": pa.array(errors[top], pa.int64()),
            "guaranteed": pa.array(counts[top] - errors[top] >= bar, pa.bool_()), "lost": pa.array([lost] * len(top), pa.int64()), "survivors": pa.array([len(labels)] * len(top), pa.int64()),
        })


def _text(labels: np.ndarray) -> pa.Array:
    return pa.array(labels.tolist(), pa.large_string() if isinstance(labels[0], str) else pa.large_binary())


def _largest(labels: np.ndarray, counts: np.ndarray, n: int) -> np.ndarray:
    """Places of the n largest counts, ties by label."""
    places = np.arange(len(counts))
    if n < len(counts):
        cut = np.partition(counts, len(counts) - n)[len(counts) - n]
        over, tied = np.flatnonzero(counts > cut), np.flatnonzero(counts == cut)
        places = np.concatenate([over, tied[_order(labels[tied], counts[tied])[: n - len(over)]]])
    return places[_order(labels[places], counts[places])]


def _order(labels: np.ndarray, counts: np.ndarray) -> np.ndarray:
    if labels.dtype == object and len(labels):
        return pc.sort_indices(pa.table({"n": counts, "item": _text(labels)}), [("n", "descending"), ("item", "ascending")]).to_numpy()
    return np.lexsort((labels, -counts))


class SpaceSaving(CounterSummary):
    """Whole Arrow batches are counted at once and enter as weighted labels. A label that a full side lacks takes that side's
    least count, as count and as error; the largest stay. `isomorphic` merges through the other sketch's rule instead: both
    sides less their least counts, merged as Misra-Gries sketches, and the least counts added back."""

    isomorphic = False

    def shrink(self, labels, counts, errors, lost):
        if len(labels) > self.capacity:
            # the state's floor: no absent label has more
            top = _largest(labels, counts, self.capacity)
            return labels[top], counts[top], errors[top], max(lost, int(np.partition(counts, len(counts) - self.capacity - 1)[len(counts) - self.capacity - 1]))
        return labels, counts, errors, lost

    def merge(self, a, b):
        if a is None or b is None:
            return b if a is None else a
        if self.isomorphic and len(a[0]) == self.capacity == len(b[0]):
            return self._through_decrements(a, b)
        labels = np.concatenate([a[0], b[0]])
        here = [np.concatenate([np.full(len(a[0]), i == 0), np.full(len(b[0]), i == 1)]) for i in (0, 1)]
        u, n, e, in_a, in_b = self._sum(labels, np.concatenate([a[1], b[1]]), np.concatenate([a[2], b[2]]), *here)
        floor = a[3] * (in_a == 0) + b[3] * (in_b == 0)
        out = self.shrink(u, n + floor, e + floor, 0)
        return (*out[:3], max(out[3], a[3] + b[3]))

    def _through_decrements(self, a, b):
        floors = int(a[1].min()), int(b[1].min())
        labels = np.concatenate([a[0], b[0]])
        over = np.concatenate([a[1] - floors[0], b[1] - floors[1]])
        u, n = self._sum(labels, over)
        cut = int(np.partition(n, len(n) - self.capacity - 1)[len(n) - self.capacity - 1]) if len(n) > self.capacity else 0
        top = _largest(u, n, self.capacity)
        counts = np.maximum(n[top] - cut, 0) + cut + sum(floors)
        # every count may be over by both floors at most, as an absent label's would
        return u[top], counts, np.full(len(top), sum(floors), np.int64), cut + sum(floors)


class IsomorphicSpaceSaving(SpaceSaving):
    isomorphic = True


class _Buckets:
    """Labels by their counts: raising one, and finding a least one, cost O(1)."""

    def __init__(self, labels=(), counts=(), errors=(), lost: int = 0):
        self.counts, self.errors, self.of, self.lost = {}, {}, {}, lost
        for label, c, e in zip(labels, counts, errors, strict=True):
            self.counts[label], self.errors[label] = c, e
            self.of.setdefault(c, {})[label] = None
        self.least = min(self.of, default=0)

    def take(self, label) -> int:
        c = self.counts.pop(label)
        bucket = self.of[c]
        del bucket[label]
        if not bucket:
            del self.of[c]
        return c

    def put(self, label, c: int) -> None:
        self.counts[label] = c
        self.of.setdefault(c, {})[label] = None


class _OneAtATime:
    """Folds row by row into `_Buckets`; arrays are made only where states meet."""

    batch_rows = 0

    def fold(self, state, batch):
        own = self.buckets(state)
        for label in self.code.encode(batch.column(0)).tolist():
            self.see(own, label)
        return own

    @staticmethod
    def buckets(state) -> _Buckets:
        if state is None or isinstance(state, _Buckets):
            return state or _Buckets()
        return _Buckets(*(x.tolist() for x in state[:3]), state[3])

    def arrays(self, state):
        if not isinstance(state, _Buckets):
            return state
        if not state.counts and not state.lost:
            return None
        labels = list(state.counts)
        kept = np.empty(len(labels), object)
        kept[:] = labels
        return (np.array(labels, np.int64) if self.code.plain else kept), np.array([state.counts[x] for x in labels], np.int64), np.array([state.errors.get(x, 0) for x in labels], np.int64), state.lost

    def dump(self, state):
        return pickle.dumps(self.arrays(state), protocol=5)

    def merge(self, a, b):
        return super().merge(self.arrays(a), self.arrays(b))

    def finalize(self, state):
        return super().finalize(self.arrays(state))

    def whole(self, state):
        return not state.lost if isinstance(state, _Buckets) else super().whole(state)

    def held(self, state):
        return len(state.counts) if isinstance(state, _Buckets) else super().held(state)

    def counted(self, state):
        return super().counted(self.arrays(state))


class StreamSummary(_OneAtATime, SpaceSaving):
    """Space-Saving one item at a time: a new label takes a least one's place and count, plus one."""

    def see(self, s: _Buckets, label) -> None:
        c = s.counts.get(label)
        if c is not None:
            s.take(label)
            s.put(label, c + 1)
        elif len(s.counts) < self.capacity:
            # labels that a merge left out may have had up to `lost`
            s.errors[label] = s.lost
            s.put(label, s.lost + 1)
            s.least = min(s.least, s.lost + 1) if len(s.counts) > 1 else s.lost + 1
            return
        else:
            out, c = next(iter(s.of[s.least])), s.least
            s.take(out)
            del s.errors[out]
            s.errors[label] = s.lost = c
            s.put(label, c + 1)
        if s.least not in s.of:
            s.least = c + 1


class MisraGries(CounterSummary):
    """Over capacity all counts fall by the first one past it, and those not positive go. Whole batches at once."""

    def shrink(self, labels, counts, errors, lost):
        if len(labels) > self.capacity:
            cut = int(np.partition(counts, len(counts) - self.capacity - 1)[len(counts) - self.capacity - 1])
            left = counts > cut
            return labels[left], counts[left] - cut, errors[left], lost + cut
        return labels, counts, errors, lost

    def merge(self, a, b):
        if a is None or b is None:
            return b if a is None else a
        u, n = self._sum(np.concatenate([a[0], b[0]]), np.concatenate([a[1], b[1]]))
        return self.shrink(u, n, np.zeros(len(u), np.int64), a[3] + b[3])


class StreamMisraGries(_OneAtATime, MisraGries):
    """One item at a time: a new label that finds no room lowers every count by one; `least` holds how far, so that only
    the labels that fall to nothing are touched."""

    def fold(self, state, batch):
        own = self.buckets(state)
        own.least = 0
        for label in self.code.encode(batch.column(0)).tolist():
            self.see(own, label)
        if own.least:
            # stored counts are those plus what was lowered since
            own = _Buckets(list(own.counts), [c - own.least for c in own.counts.values()], [0] * len(own.counts), own.lost)
        return own

    def see(self, s: _Buckets, label) -> None:
        if label in s.counts:
            s.put(label, s.take(label) + 1)
        elif len(s.counts) < self.capacity:
            s.put(label, s.least + 1)
        else:
            s.least += 1
            s.lost += 1
            for gone in s.of.pop(s.least, {}):
                del s.counts[gone]
