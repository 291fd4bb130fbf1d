"""Concatenated token ids with Elias-Fano document boundaries.

The file format is a Parquet table of blocks. A block holds the ids of consecutive documents as one little-endian
array and the ends of those documents as an Elias-Fano sequence: the low bits of each end packed, the high bits
in unary. `select` reads the k-th end from the high bits with a count per 64-bit word, so no table of 64-bit offsets
is stored. A block also carries the ids before it in its range; bases of the ranges are one number each.

Null texts are empty, so each document has at least its end id. doc_id must be an integer column (a string that names
none is an error). Equal doc_ids, also of identical rows, stay apart, in text order; a null doc_id comes first. Other
columns of the input, whatever their names, are not stored. An empty table gives no blocks. A text of any length is one document
and may make a block longer than `block_ids`.
"""

from __future__ import annotations

import functools
import json
import uuid
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import ragged, shuffle_width, slices, written
from .vocabulary import library_tokenizer, vocabulary
from .word_store import WordStore, encode_parts, encode_texts, one_piece

BLOCK_IDS = 1 << 20
MARK, WORDS_A_CALL, STORE_WORDS = "\0", 500, 600_000
SPLITTER = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
BLOCK_SCHEMA = "range_no int, block_no int, ids_before long, n_docs int, n_ids long, low_bits int, width int, doc_ids array<long>, low binary, high binary, ids binary"


class EliasFano:
    def __init__(self, n: int, low_bits: int, low: bytes, high: bytes):
        self.n, self.low_bits, self.low, self.high = n, low_bits, low, high
        words = np.frombuffer(high + b"\0" * (-len(high) % 8), np.uint64)
        self.rank = np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int64)])

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        """`values` ascend; an empty sequence takes no bits."""
        n = len(values)
        if not n:
            return cls(0, 0, b"", b"")
        bits = max(0, int(values[-1] // n).bit_length() - 1)
        upper = values >> bits
        flags = np.zeros(int(upper[-1]) + n, bool)
        flags[upper + np.arange(n)] = True
        part = (values[:, None] >> np.arange(bits)) & 1
        return cls(n, bits, np.packbits(part.astype(bool).ravel(), bitorder="little").tobytes(), np.packbits(flags, bitorder="little").tobytes())

    def select(self, k: int) -> int:
        word = int(np.searchsorted(self.rank, k, side="right")) - 1
        raw = int.from_bytes(self.high[8 * word : 8 * word + 8], "little")
        for _ in range(k - int(self.rank[word])):
            raw &= raw - 1
        upper = 64 * word + (raw & -raw).bit_length() - 1 - k
        at = k * self.low_bits
        chunk = int.from_bytes(self.low[at // 8 : (at + self.low_bits + 7) // 8], "little") >> (at % 8)
        return upper << self.low_bits | chunk & ((1 << self.low_bits) - 1)

    def select_many(self, ks: np.ndarray) -> np.ndarray:
        """`select` of many: the word by its count of ones before, the byte within by its own, the bit by a table."""
        ks = np.asarray(ks, np.int64)
        if not len(ks):
            return np.zeros(0, np.int64)
        word = np.searchsorted(self.rank, ks, side="right") - 1
        left = ks - self.rank[word]
        raw = np.frombuffer(self.high + b"\0" * (-len(self.high) % 8), np.uint8).reshape(-1, 8)[word]
        upto = np.cumsum(np.bitwise_count(raw), axis=1, dtype=np.int64)
        byte = (upto <= left[:, None]).sum(axis=1)
        row = np.arange(len(ks))
        left = left - np.where(byte > 0, upto[row, byte - 1], 0)
        upper = 64 * word + 8 * byte + _ones_of_byte()[raw[row, byte], left] - ks
        # low bits start anywhere in a byte and span at most nine of them
        at = ks * self.low_bits
        padded = np.frombuffer(self.low + b"\0" * 9, np.uint8)
        low = np.zeros(len(ks), np.uint64)
        for i in range(8):
            low |= padded[at // 8 + i].astype(np.uint64) << np.uint64(8 * i)
        shift = (at % 8).astype(np.uint64)
        low >>= shift
        if self.low_bits > 56:
            spill = padded[at // 8 + 8].astype(np.uint64)
            low |= np.where(shift > 0, spill << (np.uint64(64) - np.maximum(shift, np.uint64(1))), np.uint64(0))
        low &= np.uint64((1 << self.low_bits) - 1)
        return upper << self.low_bits | low.view(np.int64)


@functools.cache
def _ones_of_byte() -> np.ndarray:
    """Place of the k-th one of each byte."""
    out = np.zeros((256, 8), np.int64)
    for b in range(256):
        ones = [i for i in range(8) if b >> i & 1]
        out[b, : len(ones)] = ones
    return out


def _splits_letters(path: str) -> bool:
    """Whether the file's normalizer is NFC, one blank for white space and lower case, and its splitter takes runs of letters,
    single numbers and runs of anything else, but for contractions after an apostrophe: what `word_parts` asks for."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    normal, split = (spec.get("normalizer") or {}).get("normalizers", []), (spec.get("pre_tokenizer") or {}).get("pretokenizers", [])
    return (
        [(n["type"], n.get("pattern"), n.get("content")) for n in normal] == [("NFC", None, None), ("Replace", {"Regex": r"\s+"}, " "), ("Lowercase", None, None)]
        and [(s["type"], s.get("pattern"), s.get("invert"), s.get("add_prefix_space"), s.get("use_regex")) for s in split] == [("Split", {"Regex": SPLITTER}, True, None, None), ("ByteLevel", None, None, False, False)]
        and split[0]["behavior"] == "Removed"
    )


@functools.lru_cache(maxsize=1)
def _encoder(path: str, run: str):
    """Ids and counts of a string array by the library. A vocabulary with word ends drops white space, so that there
    each distinct word, or part of a word, goes to the library once; any other gets whole texts.

    The words met stay for the tasks that this process gets of the same `run`, at most STORE_WORDS and one slice's.
    """
    tokenizer, vocab = library_tokenizer(path), vocabulary(path)

    def whole(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        found = [e.ids for e in tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        counts = np.fromiter(map(len, found), np.int64, len(found))
        return np.fromiter(chain.from_iterable(found), np.int64, int(counts.sum())), counts

    if not vocab.suffix:
        return lambda texts: whole(texts.to_pylist())
    mark = tokenizer.encode(MARK, add_special_tokens=False).ids
    closes = np.array([label.endswith(vocab.suffix) for label in vocab.labels])

    def flat_ids(words: list[str], between: str) -> np.ndarray:
        # a few hundred words a call
        texts = [between.join([*words[i : i + WORDS_A_CALL], ""]) for i in range(0, len(words), WORDS_A_CALL)]
        return np.concatenate([np.zeros(0, np.int64), *[np.array(e.ids, np.int64) for e in tokenizer.encode_batch_fast(texts, add_special_tokens=False)]])

    def words_encoded(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        # parted by a mark whose one id no other text gives
        if len(mark) != 1 or any(MARK in w for w in words):
            return whole(words)
        flat = flat_ids(words, f" {MARK} ")
        marks = flat == mark[0]
        return flat[~marks], np.diff(np.flatnonzero(marks), prepend=-1) - 1

    def parts_encoded(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        # a word of one piece needs no mark: its last id alone closes a word
        one = one_piece(words)
        flat = flat_ids([words[i] for i in np.flatnonzero(one)], " ")
        last = np.flatnonzero(closes[flat])
        if len(last) != one.sum() or len(last) and last[-1] != len(flat) - 1:
            return words_encoded(words)
        other_flat, other = words_encoded([words[i] for i in np.flatnonzero(~one)])
        counts, starts = np.empty(len(words), np.int64), np.empty(len(words), np.int64)
        counts[one], counts[~one] = np.diff(last, prepend=-1), other
        starts[one], starts[~one] = np.cumsum(counts[one]) - counts[one], len(flat) + np.cumsum(other) - other
        return np.concatenate([flat, other_flat])[ragged(starts, counts)], counts

    if _splits_letters(path):
        store = WordStore(parts_encoded, STORE_WORDS)
        return lambda texts: encode_parts(store, texts, vocab.special)
    store = WordStore(words_encoded, STORE_WORDS)
    return lambda texts: encode_texts(store, texts, vocab.special)


def write_blocks(spark: SparkSession, docs: DataFrame, path: str, end_id: int, block_ids: int = BLOCK_IDS) -> DataFrame:
    """Encodes every whole text, appends `end_id`, and writes blocks in ascending doc_id order; returns the written table."""
    ranges = shuffle_width(spark)
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).repartitionByRange(ranges, "doc_id").sortWithinPartitions("doc_id", "text")
    numbered = ordered.select(F.spark_partition_id().alias("range_no"), "doc_id", "text")
    name = uuid.uuid4().hex

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = library_tokenizer(path)
        dtype = np.uint16 if tokenizer.get_vocab_size() <= 1 << 16 and end_id < 1 << 16 else np.uint32
        encode = _encoder(path, name)
        docs_in, parts, ends, before, block_no, range_no = [], [], [], 0, 0, 0

        def flush():
            nonlocal docs_in, parts, ends, before, block_no
            ef = EliasFano.of(np.array(ends, np.int64))
            row = [range_no, block_no, before, len(docs_in), ends[-1], ef.low_bits, np.dtype(dtype).itemsize, docs_in, ef.low, ef.high, np.concatenate(parts).tobytes()]
            before, block_no = before + ends[-1], block_no + 1
            docs_in, parts, ends = [], [], []
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, _TYPES, strict=True)], names=_NAMES)

        for batch in batches:
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("text")
            range_no = batch.column("range_no")[0].as_py() if len(batch) else range_no
            for low, high in slices(texts):
                flat, counts = encode(texts[low:high])
                stops = np.cumsum(counts)
                for doc, a, b in zip(ids[low:high], (stops - counts).tolist(), stops.tolist(), strict=True):
                    own = np.append(flat[a:b], end_id).astype(dtype)
                    docs_in.append(doc)
                    parts.append(own)
                    ends.append((ends[-1] if ends else 0) + len(own))
                    if ends[-1] >= block_ids:
                        yield flush()
        if docs_in:
            yield flush()

    return written(spark, numbered.mapInArrow(run, BLOCK_SCHEMA), "token-blocks")


_NAMES = [c.split()[0] for c in BLOCK_SCHEMA.split(", ")]
_TYPES = [pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.int64()), pa.binary(), pa.binary(), pa.binary()]


def read_blocks(blocks: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, from the blocks alone.

    Only one total for each range (as many as write tasks) is gathered on the driver.
    """
    totals = sorted((r.range_no, r.n) for r in blocks.groupBy("range_no").agg(F.sum("n_ids").alias("n")).collect())
    bases, total = {}, 0
    for k, n in totals:
        bases[k], total = total, total + n

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                ends = EliasFano(r["n_docs"], r["low_bits"], r["low"], r["high"]).select_many(np.arange(r["n_docs"]))
                starts = np.concatenate([[0], ends[:-1]])
                ids = np.frombuffer(r["ids"], np.uint16 if r["width"] == 2 else np.uint32).astype("<u4")
                crc = [zlib.crc32(ids[a:b].tobytes()) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(r["doc_ids"], pa.int64()), pa.array(starts + bases[r["range_no"]] + r["ids_before"], pa.int64()), pa.array(ends - starts, pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return blocks.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def fetch(blocks: DataFrame, doc_ids: list[int]) -> DataFrame:
    """doc_id, ids of the named documents (a caller's short list): blocks without them are passed over, and of the others
    only the ends beside a wanted document are read, by `select`."""
    wanted = frozenset(doc_ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                ef = EliasFano(r["n_docs"], r["low_bits"], r["low"], r["high"])
                ids = np.frombuffer(r["ids"], np.uint16 if r["width"] == 2 else np.uint32).astype(np.int32)
                at = [i for i, d in enumerate(r["doc_ids"]) if d in wanted]
                found = [ids[ef.select(i - 1) if i else 0 : ef.select(i)] for i in at]
                yield pa.RecordBatch.from_arrays([pa.array([r["doc_ids"][i] for i in at], pa.int64()), pa.array(found, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    held = blocks.where(F.arrays_overlap("doc_ids", F.array(*[F.lit(d).cast("long") for d in sorted(wanted)])))
    return held.mapInArrow(run, "doc_id long, ids array<int>")
