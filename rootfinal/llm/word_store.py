"""Encodes texts by their distinct words: a white-space separated word is encoded once, then looked up."""

from __future__ import annotations

from collections.abc import Callable, Iterable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .shared import ragged, sums_by_run


class WordStore:
    """Ids of words met so far. `encode(words)` gives the ids of new words, concatenated, and the number of each word's.

    It only saves work: past `limit` words it starts anew, and results never depend on it.
    """

    def __init__(self, encode: Callable[[list[str]], tuple[np.ndarray, np.ndarray]], limit: int = 200_000):
        self.encode, self.limit = encode, limit
        self._clear()

    def _clear(self) -> None:
        self.index: dict[str, int] = {}
        self.ids = np.zeros(1 << 16, np.int32)
        self.starts = np.zeros(1 << 12, np.int64)
        self.counts = np.zeros(1 << 12, np.int64)
        self.used = 0

    def rows(self, words: list[str]) -> np.ndarray:
        """The row of each of these distinct words."""
        if len(self.index) > self.limit:
            self._clear()
        get = self.index.get
        at = np.fromiter((get(w, -1) for w in words), np.int64, len(words))
        missing = np.flatnonzero(at < 0)
        if len(missing):
            new = [words[i] for i in missing]
            flat, counts = self.encode(new)
            first = len(self.index)
            self.index.update(zip(new, range(first, first + len(new)), strict=True))
            at[missing] = np.arange(first, first + len(new))
            self._grow(first + len(new), self.used + len(flat))
            self.counts[first : first + len(new)] = counts
            self.starts[first : first + len(new)] = self.used + np.cumsum(counts) - counts
            self.ids[self.used : self.used + len(flat)] = flat
            self.used += len(flat)
        return at

    def _grow(self, words: int, ids: int) -> None:
        for name, size in (("starts", words), ("counts", words), ("ids", ids)):
            old = getattr(self, name)
            if size > len(old):
                new = np.zeros(max(size, 2 * len(old)), old.dtype)
                new[: len(old)] = old
                setattr(self, name, new)


def split_words(texts: pa.Array, special: Iterable[str]) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """ASCII white-space words of texts without null: (index of each word's distinct form, the forms, each text's last word).

    Special strings become words of their own wherever they stand, as the library cuts them out first.
    """
    for s in special:
        if pc.any(pc.match_substring(texts, s)).as_py():
            texts = pc.replace_substring(texts, s, f" {s} ")
    lists = pc.ascii_split_whitespace(texts)
    coded = lists.flatten().dictionary_encode()
    ends = lists.offsets.to_numpy()[1:].astype(np.int64) - lists.offsets[0].as_py()
    return coded.indices.to_numpy(zero_copy_only=False), coded.dictionary, ends


def encode_texts(store: WordStore, texts: pa.Array, special: Iterable[str]) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts, concatenated, and the number of ids of each."""
    index, words, ends = split_words(texts, special)
    rows = store.rows(words.to_pylist())[index]
    counts = store.counts[rows]
    return store.ids[ragged(store.starts[rows], counts)], sums_by_run(counts, ends)


def _byte_tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each byte, first of all and then behind 0xC3: its kind (1 letter, 2 symbol, 0 neither); its lower case.

    Letters are those of ASCII and of Latin-1 behind 0xC3. An apostrophe may start a contraction and is neither.
    """
    kind, behind, lower = np.zeros(256, np.int8), np.zeros(256, np.int8), np.arange(512, dtype=np.int64).reshape(2, 256) & 255
    for b in range(0x21, 0x7F):
        kind[b] = 1 if chr(b).isalpha() else 2 if not chr(b).isdigit() and chr(b) != "'" else 0
        lower[0, b] = ord(chr(b).lower())
    kind[0xC3] = 1
    for c in map(chr, range(0xC0, 0x100)):
        behind[ord(c) - 0x40] = c.isalpha()
        if 0xC0 <= ord(c.lower()) <= 0xFF:
            lower[1, ord(c) - 0x40] = ord(c.lower()) - 0x40
    return kind, behind, lower.astype(np.uint8)


_KIND, _BEHIND, _LOWER = _byte_tables()


def letters_then_symbols(words: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(whether each word is letters and then symbols, either of them maybe none; its bytes of letters; where it ends in the bytes;
    these bytes, in lower case where the word is such)."""
    words = words.cast(pa.string())
    edges = np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + len(words) + 1].astype(np.int64)
    raw = np.frombuffer(words.buffers()[2] or b"", np.uint8)[edges[0] : edges[-1]]
    edges -= edges[0]
    after = np.zeros(len(raw), bool)
    after[1:] = raw[:-1] == 0xC3
    kind = np.where(after, _BEHIND[raw], _KIND[raw])
    odd = kind == 0
    again = np.flatnonzero((kind[1:] == 1) & (kind[:-1] == 2)) + 1
    starts = np.zeros(len(raw) + 1, bool)
    starts[edges] = True
    odd[again[~starts[again]]] = True
    fits, letters = (np.diff(np.concatenate([[0], np.cumsum(x, dtype=np.int64)])[edges]) for x in (odd, kind == 1))
    fits = fits == 0
    return fits, letters, edges[1:], np.where(np.repeat(fits, np.diff(edges)), _LOWER[after.view(np.uint8), raw], raw)


def one_piece(words: list[str]) -> np.ndarray:
    """Whether each word is letters alone or symbols alone."""
    array = pa.array(words, pa.string())
    fits, letters, _, _ = letters_then_symbols(array)
    return fits & ((letters == 0) | (letters == pc.binary_length(array).to_numpy(zero_copy_only=False)))


def word_parts(words: pa.Array) -> tuple[np.ndarray, list[str], np.ndarray]:
    """(index of each part's form, the distinct forms, each word's last part), for splitters that part letters from symbols and
    ignore case: a word of letters and then symbols is its letters in lower case and its symbols, any other stays whole."""
    fits, letters, stops, raw = letters_then_symbols(words)
    begin = np.concatenate([[0], stops[:-1]])
    two = fits & (letters > 0) & (letters < stops - begin)
    ends = np.cumsum(1 + two)
    edges = np.zeros(len(words) + int(two.sum()) + 1, np.int32)
    edges[ends] = stops
    edges[ends[two] - 1] = (begin + letters)[two]
    parts = pa.StringArray.from_buffers(len(edges) - 1, pa.py_buffer(edges), pa.py_buffer(raw))
    coded = parts.dictionary_encode()
    return coded.indices.to_numpy(zero_copy_only=False), coded.dictionary.to_numpy(zero_copy_only=False).tolist(), ends


def encode_parts(store: WordStore, texts: pa.Array, special: Iterable[str]) -> tuple[np.ndarray, np.ndarray]:
    """`encode_texts` with a store of `word_parts`: the ids of each distinct word are put together from its parts' first."""
    index, words, ends = split_words(texts, special)
    parts, forms, part_ends = word_parts(words)
    rows = store.rows(forms)[parts]
    counts = store.counts[rows]
    ids = store.ids[ragged(store.starts[rows], counts)]
    of_word = sums_by_run(counts, part_ends)
    counts = of_word[index]
    return ids[ragged((np.cumsum(of_word) - of_word)[index], counts)], sums_by_run(counts, ends)
