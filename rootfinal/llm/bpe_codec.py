"""BPE encoding and decoding by the merge automaton.

`encode_ids` gives the ids of every row and `decode_ids` their text again; digests of both are a view over these.
Null and empty texts encode to no ids; texts of any length are taken whole. Rows, also repeated ones, are independent, so ties
cannot occur; an empty table gives no rows. A kept column named like an output gets `_in` behind its name.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .merge_automaton import automaton
from .shared import carried, slices, sums_by_run, text_array, trimmed
from .vocabulary import byte_letters, library_splitter, vocabulary
from .word_store import WordStore, encode_texts

SLICE, STORE_WORDS = 2 << 20, 120_000  # bytes of text encoded at once, words kept between slices
DECODE_IDS = 1 << 20  # ids whose labels are held at once
AT_ONCE = 1 << 14  # words that the splitter takes in one call
_BYTE = {ord(letter): b for b, letter in enumerate(byte_letters())}


def _normal(tokenizer, words: list[str]) -> list[str]:
    """The words as the normalizer leaves them: those of ASCII letters in one call, where each must keep its place, others one by one."""
    plain = [i for i, w in enumerate(words) if w.isascii()]
    out = list(words)
    joined = " ".join([words[i] for i in plain])
    normal = tokenizer.normalizer.normalize_str(joined)
    if normal.count(" ") == joined.count(" ") and len(normal) == len(joined):
        for i, w in zip(plain, normal.split(" ") if plain else [], strict=True):
            out[i] = w
    else:
        plain = []
    for i in set(range(len(words))).difference(plain):
        out[i] = tokenizer.normalizer.normalize_str(words[i])
    return out


def split_pieces(tokenizer, words: list[str]) -> tuple[bytes, np.ndarray, np.ndarray]:
    """(bytes of all pieces, the length of each, the number of each word's) of white-space free words.

    The splitter takes all words in one call, a blank between two: no piece holds white space, so none reaches over a blank, and
    the place where a piece starts tells its word.
    """
    words = _normal(tokenizer, words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    split = tokenizer.pre_tokenizer.pre_tokenize_str(" ".join(words))
    lengths = np.fromiter((len(p) for p, _ in split), np.int64, len(split))
    starts = np.fromiter((span[0] for _, span in split), np.int64, len(split))
    owners = np.searchsorted(ends, starts, side="right")
    return "".join([p for p, _ in split]).translate(_BYTE).encode("latin-1"), lengths, np.bincount(owners, minlength=len(words))


def word_encoder(path: str):
    """Encodes white-space free words: the library's normalizer and splitter, then the automaton's arcs."""
    tokenizer, auto, special = library_splitter(path), automaton(path), vocabulary(path).special

    def plain(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        raw, lengths, pieces = split_pieces(tokenizer, words)
        tokens, counts = auto.encode_pieces(raw, lengths)
        return tokens, sums_by_run(counts, np.cumsum(pieces))

    def encode(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids, counts, low = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
        for cut in [*(i for i, w in enumerate(words) if w in special), len(words)]:
            for start in range(low, cut, AT_ONCE):
                tokens, n = plain(words[start : min(start + AT_ONCE, cut)])
                ids.append(tokens)
                counts.append(n)
            if cut < len(words):
                ids.append(np.array([special[words[cut]]]))
                counts.append(np.array([1]))
            low = cut + 1
        return np.concatenate(ids), np.concatenate(counts)

    return encode


def encode_ids(df: DataFrame, path: str, keep: list[str], text: str = "text") -> DataFrame:
    """`keep` columns plus n_tokens and ids of the whole text."""
    base = df.select(*carried(keep, ["n_tokens", "ids", "decoded", "ids_sha256", "decoded_sha256"]), F.col(text).alias("__text"))
    schema = T.StructType([*base.schema.fields[:-1], T.StructField("n_tokens", T.LongType()), T.StructField("ids", T.ArrayType(T.IntegerType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, special = WordStore(word_encoder(path), STORE_WORDS), vocabulary(path).special
        for batch in batches:
            texts = text_array(batch.column("__text"))
            for low, high in slices(texts, SLICE):
                ids, counts = encode_texts(store, texts.slice(low, high - low), special)
                ends = np.concatenate([[0], np.cumsum(counts)])
                part = batch.slice(low, high - low)
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(ids, pa.int32()))
                yield pa.RecordBatch.from_arrays([*[part.column(i) for i in range(len(keep))], pa.array(counts, pa.int64()), lists], names=[f.name for f in schema])

    return base.mapInArrow(trimmed(run), schema)


def _parts(batch: pa.RecordBatch, place: int) -> Iterator[tuple[pa.RecordBatch, pa.ListArray]]:
    """The batch in slices of at most DECODE_IDS ids (a longer row stands alone), each with its lists of ids."""
    ends = np.cumsum(pc.fill_null(pc.list_value_length(batch.column(place)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    low = 0
    while low < len(batch):
        done = ends[low - 1] if low else 0
        high = max(low + 1, int(np.searchsorted(ends, done + DECODE_IDS, side="right")))
        part = batch.slice(low, high - low)
        yield part, part.column(place)
        low = high


def _joined(lists: pa.ListArray, names: pa.Array) -> pa.Array:
    """The names of each list's ids, joined by one space; null for a null list."""
    edges = np.concatenate([[0], np.cumsum(pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False))])
    words = pa.ListArray.from_arrays(pa.array(edges, pa.int32()), names.take(lists.flatten()))
    return pc.if_else(lists.is_valid(), pc.binary_join(words, " "), None)


def decode_ids(encoded: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """`encoded` plus `decoded`: labels joined by one space, as the library joins where a vocabulary names no decoder."""
    schema = T.StructType([*encoded.schema.fields, T.StructField("decoded", T.StringType())])
    place = encoded.columns.index(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels = pa.array(vocabulary(path).labels)
        for batch in batches:
            for part, lists in _parts(batch, place):
                yield pa.RecordBatch.from_arrays([*part.columns, _joined(lists, labels)], names=[f.name for f in schema])

    return encoded.mapInArrow(run, schema)


def digests(encoded: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """`encoded` with ids_sha256 and decoded_sha256 in place of the ids, both derived from that column alone."""
    place = encoded.columns.index(ids)
    fields = [f for f in encoded.schema.fields if f.name != ids]
    schema = T.StructType([*fields, T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels = pa.array(vocabulary(path).labels)
        numbers = pa.array(map(str, range(len(labels))))
        for batch in batches:
            for part, lists in _parts(batch, place):
                shas = [pa.array([None if t is None else hashlib.sha256(t.encode()).hexdigest() for t in _joined(lists, names).to_pylist()], pa.string()) for names in (numbers, labels)]
                yield pa.RecordBatch.from_arrays([*[c for i, c in enumerate(part.columns) if i != place], *shas], names=[f.name for f in schema])

    return encoded.mapInArrow(run, schema)


def encode_column(df: DataFrame, path: str, keep: list[str], text: str = "text") -> DataFrame:
    """`keep` columns plus n_tokens, ids_sha256 and decoded_sha256 of the whole text."""
    return digests(encode_ids(df, path, keep, text), path)
