"""A deterministic automaton over tokens that accepts exactly the BPE tokenizations.

Construction. Start with one state that loops on every base symbol. Apply the merges in priority order,
each as a gadget: for merge (a, b) -> c every path `s -a-> q -b-> t` is redirected so that `q` loses its
`b` arc after `a`, and `s` gains `c -> t`. As all arcs that carry a token lead to one state, a state is
named by the token read last, and the gadget is three rules on the relation "token y may follow token x":

    (a, b) is removed;   (s, c) takes the value of (s, a);   (c, t) takes the value that (b, t) had.

States are kept copy-on-write: the row of `c` is the row of `b` as of that merge, and its column is the
column of `a`, so compiling 50,000 gadgets stores three integers each in place of 50,000 x 50,000 arcs.
An arc is materialised when a word first needs it, by walking those copies back in time, and kept in a table.

Encoding. Each prefix of a word has exactly one accepted path. Its last token ends there, so it is one of
the vocabulary's suffixes at that place, found with a suffix-link trie; the arc table says which one may follow the
token before it. Words of a block step through the tables together, one symbol a step; the path is read back
from the word's end and its arc labels are the tokens.
"""

from __future__ import annotations

import functools
from collections import deque

import numpy as np

from .shared import ragged
from .vocabulary import END, Vocabulary, vocabulary

_MIX = np.uint64(0x9E3779B97F4A7C15)  # odd, golden ratio: spreads keys over table slots
LOCKSTEP_MAX = 192  # symbols; longer words walk alone, in linear time and memory
BLOCK_CELLS = 3 << 20


class IntTable:
    """Fixed open-addressing map from non-negative int64 keys to int64 values, looked up in bulk."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.bits = max(4, int(np.ceil(np.log2(max(1, len(keys)) * 4))))
        self.mask = (1 << self.bits) - 1
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.values = np.full(1 << self.bits, -1, np.int64)
        at, left = self._slot(keys), np.arange(len(keys))
        while len(left):
            free = self.keys[at] < 0
            first = np.zeros(len(left), bool)
            first[np.unique(at, return_index=True)[1]] = True
            put = free & first
            self.keys[at[put]] = keys[left[put]]
            self.values[at[put]] = values[left[put]]
            left, at = left[~put], (at[~put] + 1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * _MIX) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, keys: np.ndarray) -> np.ndarray:
        """Values of `keys`, -1 where absent."""
        at = self._slot(keys)
        found = self.keys[at]
        out = self.values[at]
        odd = np.flatnonzero((found != keys) & (found >= 0))
        out[found != keys] = -1
        at = at[odd]
        while len(odd):
            at = (at + 1) & self.mask
            found = self.keys[at]
            hit = found == keys[odd]
            out[odd[hit]] = self.values[at[hit]]
            go = ~hit & (found >= 0)
            odd, at = odd[go], at[go]
        return out


class MergeAutomaton:
    def __init__(self, vocab: Vocabulary):
        self.vocab = vocab
        n = max(vocab.symbols, default=0) + 1
        self.left = np.full(n, -1, np.int64)
        self.right = np.full(n, -1, np.int64)
        self.born = np.full(n, -1, np.int64)  # index of the gadget that made the token, -1 for base symbols
        a, b, c = vocab.merges.T
        order = np.arange(len(c))
        self.left[c], self.right[c], self.born[c] = a, b, order
        self.pairs = IntTable(a << 16 | b, order)
        self.length = np.zeros(n, np.int64)
        for i, s in vocab.symbols.items():
            self.length[i] = len(s)
        # arcs seen so far, direct-mapped: a slot holds one (from, to) key and whether the arc exists
        self._arc_key = np.full(1 << 20, -1, np.int64)
        self._arc_on = np.zeros(1 << 20, bool)
        self.reached = np.ones(n, bool)
        self._compile_reached(a, b, c, order)
        self._compile_trie()

    def _compile_reached(self, a, b, c, order) -> None:
        """A gadget whose path a, b never arises makes a token no text yields; such tokens get no arcs."""
        while True:
            made = self._follows(a, b, order) & self.reached[a] & self.reached[b]
            if (self.reached[c] == made).all():
                return
            self.reached[c] = made

    def _follows(self, x: np.ndarray, y: np.ndarray, limit: np.ndarray) -> np.ndarray:
        """Whether y may follow x once the gadgets before `limit` are applied: the copies walked back."""
        x, y, limit = x.copy(), y.copy(), limit.copy()
        out = np.ones(len(x), bool)
        live = np.arange(len(x))
        while len(live):
            p, q, k = x[live], y[live], limit[live]
            rank = self.pairs.get(p << 16 | q)
            gone = (rank >= 0) & (rank < k)
            out[live[gone]] = False
            bp, bq = self.born[p], self.born[q]
            base = (bp < 0) & (bq < 0)
            go = ~gone & ~base
            live, p, q, bp, bq = live[go], p[go], q[go], bp[go], bq[go]
            row = bp > bq  # the newer token decides: a row is the copy of its right part, a column of its left part
            x[live] = np.where(row, self.right[p], p)
            y[live] = np.where(row, q, self.left[q])
            limit[live] = np.where(row, bp, bq + 1)
        return out

    def arcs(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Whether the arcs x -> y exist, from the table; absent ones are materialised first."""
        key = x << 16 | y
        at = ((key.astype(np.uint64) * _MIX) >> np.uint64(44)).astype(np.int64)
        on = self._arc_on[at]
        miss = np.flatnonzero(self._arc_key[at] != key)
        if len(miss):
            new, back = np.unique(key[miss], return_inverse=True)
            value = self._follows(new >> 16, new & 0xFFFF, np.full(len(new), len(self.vocab.merges))) & self.reached[new & 0xFFFF]
            on[miss] = value[back]
            self._arc_key[at[miss]] = key[miss]
            # the slot's last writer counts, so read back which key it holds
            slot_key = self._arc_key[at[miss]]
            self._arc_on[at[miss]] = value[np.searchsorted(new, slot_key)]
        return on

    def may_follow(self, x: int, y: int) -> bool:
        """One arc, as `_follows` finds it, at the end of all gadgets."""
        if not self.reached[y]:
            return False
        pairs, born, left, right, limit = self._pair_of, self._born, self._left, self._right, len(self.vocab.merges)
        while True:
            rank = pairs.get(x << 16 | y)
            if rank is not None and rank < limit:
                return False
            a, b = born[x], born[y]
            if a < 0 and b < 0:
                return True
            if a > b:
                x, limit = right[x], a
            else:
                y, limit = left[y], b + 1

    @functools.cached_property
    def _pair_of(self) -> dict[int, int]:
        a, b, _ = self.vocab.merges.T
        return dict(zip((a << 16 | b).tolist(), range(len(a)), strict=True))

    @functools.cached_property
    def _born(self) -> list[int]:
        return self.born.tolist()

    @functools.cached_property
    def _left(self) -> list[int]:
        return self.left.tolist()

    @functools.cached_property
    def _right(self) -> list[int]:
        return self.right.tolist()

    def _compile_trie(self) -> None:
        """Trie of the tokens' symbols; `fail` of a node is its longest proper suffix in the trie,
        `out` the longest token that ends there, `shorter` of a token its longest proper suffix token."""
        arcs: dict[int, int] = {}
        token = [-1]
        for i, syms in self.vocab.symbols.items():
            if not self.reached[i]:
                continue
            u = 0
            for s in syms:
                v = arcs.get(u << 9 | s)
                if v is None:
                    arcs[u << 9 | s] = v = len(token)
                    token.append(-1)
                u = v
            token[u] = i
        below: list[list[tuple[int, int]]] = [[] for _ in token]
        for key, v in arcs.items():
            below[key >> 9].append((key & 511, v))
        fail, out = [0] * len(token), [-1] * len(token)
        shorter = [-1] * len(self.length)
        queue = deque([0])
        while queue:
            u = queue.popleft()
            for s, v in below[u]:
                if u:
                    f = fail[u]
                    while f and (f << 9 | s) not in arcs:
                        f = fail[f]
                    fail[v] = arcs.get(f << 9 | s, 0)
                if token[v] >= 0:
                    out[v] = token[v]
                    shorter[token[v]] = out[fail[v]]
                else:
                    out[v] = out[fail[v]]
                queue.append(v)
        self.trie = IntTable(np.fromiter(arcs.keys(), np.int64, len(arcs)), np.fromiter(arcs.values(), np.int64, len(arcs)))
        self.fail, self.out, self.shorter = (np.array(v, np.int64) for v in (fail, out, shorter))

    @functools.cached_property
    def _arcs(self) -> dict[int, int]:
        """The trie's arcs for steps one by one, parents first; made when the first long word needs them."""
        held = np.flatnonzero(self.trie.keys >= 0)
        held = held[np.argsort(self.trie.values[held])]
        return dict(zip(self.trie.keys[held].tolist(), self.trie.values[held].tolist(), strict=True))

    # -- encoding ---------------------------------------------------------------------------------

    def encode(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Tokens of the words (none empty), one after the other, and the number of tokens of each."""
        return self.encode_pieces(b"".join(words), np.fromiter(map(len, words), np.int64, len(words)))

    def encode_pieces(self, raw: bytes, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """`encode` of words that stand one after the other in `raw`; the last byte of each is marked if words end."""
        flat = np.frombuffer(raw, np.uint8).astype(np.int64)
        if self.vocab.suffix:
            flat[np.cumsum(lengths) - 1] += END
        starts = np.cumsum(lengths) - lengths
        counts = np.zeros(len(lengths), np.int64)
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        order = np.argsort(-lengths, kind="stable")
        low = int(np.searchsorted(-lengths[order], -LOCKSTEP_MAX))
        for w in order[:low]:
            tokens = self._walk(flat[starts[w] : starts[w] + lengths[w]].tolist())
            counts[w] = len(tokens)
            found.append((np.array([w]), np.array([len(tokens)]), np.array(tokens, np.int64)))
        while low < len(order):
            width = max(1, BLOCK_CELLS // (int(lengths[order[low]]) + 1))
            block = order[low : low + width]
            tokens, n = self._lockstep(flat, starts[block], lengths[block])
            counts[block] = n
            found.append((block, n, tokens))
            low += width
        out = np.empty(int(counts.sum()), np.int64)
        at = np.cumsum(counts) - counts
        for block, n, tokens in found:
            out[ragged(at[block], n)] = tokens
        return out, counts

    def _lockstep(self, flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The words are in order of falling length, so that those still running stand in front."""
        longest, width = int(lengths[0]), len(lengths)
        last = np.full((longest + 1, width), -1, np.int32)
        node = np.zeros(width, np.int64)
        running = np.searchsorted(-lengths, -np.arange(longest), side="left")
        for i in range(longest):
            n = int(running[i])
            sym = flat[starts[:n] + i]
            u = node[:n].copy()
            step = self.trie.get(u << 9 | sym)
            lost = np.flatnonzero((step < 0) & (u > 0))
            while len(lost):
                u[lost] = self.fail[u[lost]]
                step[lost] = self.trie.get(u[lost] << 9 | sym[lost])
                lost = lost[(step[lost] < 0) & (u[lost] > 0)]
            np.maximum(step, 0, out=step)
            node[:n] = step
            todo = np.arange(n)
            t = self.out[step]
            while True:
                if (t < 0).any():
                    raise ValueError("the vocabulary lacks a base symbol")
                back = i + 1 - self.length[t]
                ok = back == 0
                rest = np.flatnonzero(~ok)
                ok[rest] = self.arcs(last[back[rest], todo[rest]].astype(np.int64), t[rest])
                last[i + 1, todo[ok]] = t[ok]
                todo, t = todo[~ok], self.shorter[t[~ok]]
                if not len(todo):
                    break
        at, live, steps, owners = lengths.copy(), np.arange(width), [], []
        while len(live):
            t = last[at[live], live].astype(np.int64)
            steps.append(t)
            owners.append(live)
            at[live] -= self.length[t]
            live = live[at[live] > 0]
        counts = np.zeros(width, np.int64)
        for live in owners:
            counts[live] += 1
        ends = np.cumsum(counts)
        out = np.empty(int(ends[-1]), np.int64)
        for k, (t, live) in enumerate(zip(steps, owners, strict=True)):
            out[ends[live] - 1 - k] = t
        return out, counts

    def _walk(self, syms: list[int]) -> list[int]:
        """One word, symbol by symbol; for words too long for a block."""
        last, u = [-1], 0
        seen: dict[int, bool] = {}
        arcs, fail, out, shorter, length = self._arcs, self.fail, self.out, self.shorter, self.length
        for i, s in enumerate(syms):
            v = arcs.get(u << 9 | s)
            while v is None and u:
                u = int(fail[u])
                v = arcs.get(u << 9 | s)
            u = v or 0
            t = int(out[u])
            while True:
                if t < 0:
                    raise ValueError("the vocabulary lacks a base symbol")
                back = i + 1 - int(length[t])
                if not back:
                    break
                key = last[back] << 16 | t
                ok = seen.get(key)
                if ok is None:
                    ok = seen[key] = bool(self.arcs(np.array([last[back]]), np.array([t]))[0])
                if ok:
                    break
                t = int(shorter[t])
            last.append(t)
        tokens, at = [], len(syms)
        while at:
            tokens.append(last[at])
            at -= int(length[last[at]])
        return tokens[::-1]


@functools.cache
def automaton(path: str) -> MergeAutomaton:
    """Compiled once in each process."""
    return MergeAutomaton(vocabulary(path))
