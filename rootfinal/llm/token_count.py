"""Token counts by a compiled finite-state transducer whose transitions carry the tokens they emit.

Splitter. A character's class (letter, number, space, other white space, other) and those beside it say whether a piece
of the vocabulary's splitter starts there; the classes are read off the library's own splitter. The byte that starts a
piece is marked, and a marked byte takes the transducer to its first state.

Transducer. After a piece's prefix a state holds the longest suffix that begins some token and, for it and each of its
own such suffixes, the token that ended before it and how many tokens lie since. The next byte settles the last token of
the longer prefix by the merge automaton's arcs, so it settles the next state and by how much the count moves: that
number stands on the transition. States and transitions are compiled when a text first needs them and kept in one
table; beyond `limit` states only those in use stay, so memory is bounded and counts never depend on it.

Chunk maps. The bytes of a slice of texts are cut into chunks that step through the table together. A chunk's state map is
its head (the bytes before its first mark, waiting for the state to the left), the counts after it, and the state it
leaves with; a chunk without a mark is all head. Composing neighbours runs the right one's head from the left one's
last state, and a prefix sum over all transitions gives every text its count. Every text goes this way, whatever its length.

Null and empty texts count 0; rows, also repeated ones, are independent, so ties cannot occur; an empty table gives no
rows. A kept column named like an output gets `_in` behind its name.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .merge_automaton import automaton
from .shared import carried, slices, text_array
from .vocabulary import library_tokenizer, vocabulary

CHUNK = 512  # bytes
SLICE = 4 << 20
STATES_MAX = 1 << 19
OTHER, LETTER, NUMBER, SPACE, BLANK, EDGE, UNKNOWN = range(7)
_MIX = np.uint64(0x9E3779B97F4A7C15)  # odd, golden ratio: spreads keys over table slots
# fixed values: the splitter's short forms, without their apostrophe
_SHORT_ONE, _SHORT_TWO = "stmd", ("re", "ve", "ll")


def code_points(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Code points of valid UTF-8 and the place of the first byte of each."""
    if not (data & 0x80).any():
        return data.astype(np.int32), np.arange(len(data))
    first = np.flatnonzero((data & 0xC0) != 0x80)
    lead = data[first].astype(np.int32)
    out = lead.copy()
    padded = np.concatenate([data, np.zeros(3, np.uint8)])
    rest = [padded[first + i].astype(np.int32) & 0x3F for i in (1, 2, 3)]
    for least, mask, n in ((0xC0, 0x1F, 1), (0xE0, 0x0F, 2), (0xF0, 0x07, 3)):
        wide = lead >= least
        value = lead[wide] & mask
        for r in rest[:n]:
            value = value << 6 | r[wide]
        out[wide] = value
    return out, first


class Splitter:
    def __init__(self, path: str):
        self.split = library_tokenizer(path).pre_tokenizer.pre_tokenize_str
        self.known = np.full(0x110000, UNKNOWN, np.uint8)

    def classes(self, points: np.ndarray) -> np.ndarray:
        """The class of each code point; one not met before is read off how the library parts `a c 1 c !` around it."""
        out = self.known[points]
        if (out == UNKNOWN).any():
            new = np.unique(points[out == UNKNOWN]).tolist()
            starts = {a for _, (a, _) in self.split("".join(f"a{chr(c)}1{chr(c)}!\n" for c in new))}
            for i, c in enumerate(new):
                after_letter, before_number, before_other = (6 * i + k in starts for k in (1, 2, 4))
                # a blank stands apart from both; the space is the one that goes with what follows it
                self.known[c] = SPACE if c == 0x20 else LETTER if not after_letter else NUMBER if not before_number else BLANK if before_other else OTHER
            out = self.known[points]
        return out

    def marks(self, data: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Whether a piece starts at each byte; texts end at `ends` (exclusive, in bytes)."""
        points, place = code_points(data)
        n = len(points)
        kind = self.classes(points)
        opens = np.zeros(n + 1, bool)
        opens[np.searchsorted(place, np.concatenate([[0], ends[:-1]]))] = True
        opens[n] = True
        before = np.concatenate([[EDGE], kind[:-1]]).astype(np.uint8)
        before[opens[:n]] = EDGE
        after = np.concatenate([kind[1:], [EDGE]]).astype(np.uint8)
        after[opens[1:]] = EDGE
        blank, was_blank = (kind == SPACE) | (kind == BLANK), (before == SPACE) | (before == BLANK)
        to_word = after <= NUMBER
        # the last white space of a run stands apart where a word follows; a word joins a space before it
        starts = np.where(blank, ~was_blank | to_word, (before != SPACE) & (before != kind))
        quote = np.flatnonzero((points == 0x27) & (before != SPACE) & (before != OTHER) & (after == LETTER))
        if len(quote):
            padded = np.concatenate([points, [0, 0]])
            sealed = np.concatenate([opens, [True]])
            one, two = padded[quote + 1], padded[quote + 2]
            size = np.where(np.isin(one, list(map(ord, _SHORT_ONE))), 2, 0)
            for a, b in _SHORT_TWO:
                size[(one == ord(a)) & (two == ord(b)) & ~sealed[quote + 2]] = 3
            quote, size = quote[size > 0], size[size > 0]
            starts[quote + 1] = False
            rest = quote + size
            rest = rest[rest < n]
            starts[rest[kind[rest] == LETTER]] = True
        out = np.zeros(len(data), bool)
        out[place[starts]] = True
        return out


class CountTransducer:
    """States are numbered from 0, the first one; `table` maps state << 8 | byte to next << 16 | (moved + 0x8000)."""

    def __init__(self, path: str, limit: int = STATES_MAX):
        self.auto, self.limit = automaton(path), limit
        self.depth = self._depths()
        self._clear()

    def _depths(self) -> list[int]:
        out = [0] * len(self.auto.fail)
        for key, v in self.auto._arcs.items():
            out[v] = out[key >> 9] + 1  # nodes are numbered as they are made, parents first
        return out

    def _clear(self) -> None:
        self.states: list[tuple] = [(0, ((0, -1, 0),))]
        self.numbers = {self.states[0]: 0}
        self._room(18)

    def _room(self, bits: int) -> None:
        self.bits, self.used = bits, 0
        self.table = np.full((1 << bits, 2), -1, np.int64)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.view(np.uint64) * _MIX) >> np.uint64(64 - self.bits)).view(np.int64)

    def _put(self, keys: np.ndarray, values: np.ndarray) -> None:
        if 2 * (self.used + len(keys)) > len(self.table):
            old = self.table[self.table[:, 0] >= 0]
            self._room(self.bits + 2)
            self._put(old[:, 0].copy(), old[:, 1].copy())
        self.used += len(keys)
        at, mask = self._slot(keys), len(self.table) - 1
        while len(keys):
            free = self.table[at, 0] < 0
            first = np.zeros(len(keys), bool)
            first[np.unique(at, return_index=True)[1]] = True
            put = free & first
            self.table[at[put], 0], self.table[at[put], 1] = keys[put], values[put]
            keys, values, at = keys[~put], values[~put], (at[~put] + 1) & mask

    def _compiled(self, state: tuple, byte: int) -> int:
        """The transition of one state and byte, its target numbered."""
        node, held = state
        auto = self.auto
        arcs, fail = auto._arcs, auto.fail
        up, v = node, arcs.get(node << 9 | byte)
        while v is None and up:
            up = int(fail[up])
            v = arcs.get(up << 9 | byte)
        if v is None:
            raise ValueError("the vocabulary lacks a base symbol")
        by_depth = {d: (last, since) for d, last, since in held}
        t = int(auto.out[v])
        while True:
            last, since = by_depth[int(auto.length[t]) - 1]
            if last < 0 or self._follows(last, t):
                break
            t = int(auto.shorter[t])
        moved = 1 - since
        chain, w = [(0, t, 0)], v
        while w:
            d = self.depth[w]
            last, since = by_depth[d - 1]
            chain.append((d, last, since + moved))
            w = int(fail[w])
        target = (v, tuple(chain))
        number = self.numbers.get(target)
        if number is None:
            number = self.numbers[target] = len(self.states)
            self.states.append(target)
        return number << 16 | moved + 0x8000

    @functools.cached_property
    def _arc(self) -> dict[int, bool]:
        return {}

    def _follows(self, x: int, y: int) -> bool:
        key = x << 16 | y
        on = self._arc.get(key)
        if on is None:
            if len(self._arc) > 1 << 21:
                self._arc.clear()
            on = self._arc[key] = self.auto.may_follow(x, y)
        return on

    def step(self, state: np.ndarray, byte: np.ndarray) -> np.ndarray:
        """next << 16 | (moved + 0x8000) of every lane."""
        key = state << 8 | byte
        at = self._slot(key)
        row = self.table[at]
        out = row[:, 1].copy()
        odd = np.flatnonzero(row[:, 0] != key)
        mask = len(self.table) - 1
        missing = []
        at, key = at[odd], key[odd]
        held = row[odd, 0]
        while len(odd):
            none = held < 0
            missing.append(odd[none])
            odd, at, key = odd[~none], (at[~none] + 1) & mask, key[~none]
            found = self.table[at]
            held, hit = found[:, 0], found[:, 0] == key
            out[odd[hit]] = found[hit, 1]
            odd, at, key, held = odd[~hit], at[~hit], key[~hit], held[~hit]
        lost = np.concatenate(missing) if missing else np.zeros(0, np.int64)
        if len(lost):
            new, back = np.unique(state[lost] << 8 | byte[lost], return_inverse=True)
            values = np.array([self._compiled(self.states[k >> 8], k & 255) for k in new.tolist()], np.int64)
            self._put(new, values)
            out[lost] = values[back]
        return out

    def kept(self, state: np.ndarray) -> np.ndarray:
        """The lanes' states under new numbers, all others forgotten, once there are more than `limit`."""
        if len(self.states) <= self.limit:
            return state
        live, back = np.unique(state, return_inverse=True)
        contents = [self.states[s] for s in live.tolist()]
        self._clear()
        for c in contents:
            if c not in self.numbers:
                self.numbers[c] = len(self.states)
                self.states.append(c)
        return np.array([self.numbers[c] for c in contents], np.int64)[back]

    def moves(self, data: np.ndarray, marks: np.ndarray, chunk: int = CHUNK) -> np.ndarray:
        """By how much each byte moves the count of tokens; the first byte must be marked."""
        width = -(-len(data) // chunk)
        size = width * chunk
        bytes_ = np.zeros(size, np.uint8)
        bytes_[: len(data)] = data
        # bytes past the end stand as pieces of their own, their moves are cut off
        marked = np.ones(size, bool)
        marked[: len(data)] = marks
        by_step = np.ascontiguousarray(bytes_.reshape(width, chunk).T)
        marked = np.ascontiguousarray(marked.reshape(width, chunk).T)
        out = np.zeros((chunk, width), np.int32)
        head = np.where(marked.any(axis=0), marked.argmax(axis=0), chunk)
        state = np.zeros(width, np.int64)
        running = np.zeros(width, bool)
        for i in range(chunk):
            running |= marked[i]
            state[marked[i]] = 0
            if running.all():
                got = self.step(state, by_step[i].astype(np.int64))
                state, out[i] = got >> 16, (got & 0xFFFF) - 0x8000
            else:
                on = np.flatnonzero(running)
                got = self.step(state[on], by_step[i, on].astype(np.int64))
                state[on], out[i, on] = got >> 16, (got & 0xFFFF) - 0x8000
            state = self.kept(state)
        # composition: a head runs from the last state to its left; an unmarked chunk hands the state on
        todo = np.flatnonzero(head > 0)
        settled = running.copy()
        while len(todo):
            ready = settled[todo - 1]
            now, todo = todo[ready], todo[~ready]
            state = self._seams(by_step, out, state, head, now, chunk)
            settled[now] = True
        return out.T.reshape(-1)[: len(data)]

    def _seams(self, by_step, out, state, head, now, chunk: int) -> np.ndarray:
        """The heads of the chunks `now` from the states to their left."""
        n, lanes = len(now), np.concatenate([state, state[now - 1]])
        for i in range(int(head[now].max(initial=0))):
            on = np.flatnonzero(head[now] > i)
            got = self.step(lanes[len(state) + on], by_step[i, now[on]].astype(np.int64))
            lanes[len(state) + on], out[i, now[on]] = got >> 16, (got & 0xFFFF) - 0x8000
            lanes = self.kept(lanes)
        state, ran = lanes[: len(lanes) - n].copy(), lanes[len(lanes) - n :]
        through = head[now] == chunk
        state[now[through]] = ran[through]
        return state


class TokenCounter:
    def __init__(self, path: str, limit: int = STATES_MAX, chunk: int = CHUNK):
        self.splitter, self.transducer, self.chunk = Splitter(path), CountTransducer(path, limit), chunk
        self.special = sorted(vocabulary(path).special, key=len, reverse=True)

    def counts(self, texts: pa.Array) -> np.ndarray:
        """Tokens of each text (none null)."""
        out = np.zeros(len(texts), np.int64)
        texts = texts.cast(pa.large_string())
        for s in self.special:
            held = np.flatnonzero(pc.match_substring(texts, s).to_numpy(zero_copy_only=False))
            if len(held):
                # the library cuts special strings out first: the parts between them are texts of their own
                parts = [t.split(s) for t in texts.take(pa.array(held)).to_pylist()]
                out[held] += [len(p) - 1 + int(self.counts(pa.array(p, pa.string())).sum()) for p in parts]
                plain = np.ones(len(texts), bool)
                plain[held] = False
                out[plain] = self.counts(texts.filter(pa.array(plain)))
                return out
        ends = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        if not len(texts) or ends[-1] == ends[0]:
            return out
        data = np.frombuffer(texts.buffers()[2], np.uint8)[ends[0] : ends[-1]]
        ends = ends - ends[0]
        full = np.flatnonzero(np.diff(ends))
        moves = self.transducer.moves(data, self.splitter.marks(data, ends[1:][full]), self.chunk)
        total = np.concatenate([[0], np.cumsum(moves, dtype=np.int64)])
        return np.diff(total[ends])

    def count(self, text: str) -> int:
        return int(self.counts(pa.array([text]))[0])


@functools.cache
def counter(path: str) -> TokenCounter:
    """Compiled once in each process."""
    return TokenCounter(path)


def count_tokens(df: DataFrame, path: str, keep: list[str], text: str = "text", limit: int = 1024) -> DataFrame:
    """`keep` plus n_bytes, n_tokens and over_limit (n_tokens > limit)."""
    base = df.select(*carried(keep, ["n_bytes", "n_tokens", "over_limit"]), F.col(text).alias("__text"))
    schema = T.StructType([*base.schema.fields[:-1], T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = counter(path)
        for batch in batches:
            texts = text_array(batch.column("__text"))
            parts = [machine.counts(texts.slice(low, high - low)) for low, high in slices(texts, SLICE)]
            n = np.concatenate(parts) if parts else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in range(len(keep))], pc.binary_length(texts).cast(pa.int64()), pa.array(n), pa.array(n > limit)], names=[f.name for f in schema])

    return base.mapInArrow(run, schema)
