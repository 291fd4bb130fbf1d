"""Near-duplicate texts by order MinHash, verified by banded alignment.

Words are runs without ASCII white space; a k-mer is five words, labelled with its occurrence number within the text. A
sketch takes the three k-mers of least hash and keeps their text order; twelve sketches are twelve bucket keys. Texts of
equal word sequence form one class at once and only one of them goes on, named by their least doc_id and their print.

In a bucket every text is first held against the bucket's least one, which joins most of a group of copies by as many pairs
as it has texts. Buckets that then still hold several groups go into cells: blocks of their texts, every two blocks
together in one task, with a signature of 64 bytes for each text. Texts that may link across groups, by signature and
length, meet once more with their words, and every such pair is held against the other. A pair links if its labelled
k-mers have a Jaccard similarity of at least 0.8 and its word alignment, within the band that this similarity
allows, keeps at least 0.8 of the longer text. So no link that would join two groups is passed over but by chance: at similarity 0.8
a signature agrees in fewer than 36 of its 64 bytes once in about a million pairs.

A text of fewer than five words is one k-mer. Texts without words (null, empty, blank) link with nothing; texts of any
length are taken whole. Links chain: a class is a connected component, named by its least doc_id, so ties cannot occur.
Rows that repeat a doc_id share one class, also where their texts differ; a null doc_id is its own class. doc_id must be an integer
column; other columns, whatever their names, are not read. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .components import components
from .shared import discard, shuffle_width, sized, trimmed, written

K, LEAST, SKETCHES, SIMILAR, SEED = 5, 3, 12, 0.8, 10
CELL, SLOTS, LIKELY = 512, 64, 36
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_SEEDS = np.random.default_rng(SEED).integers(1, 1 << 63, SKETCHES, dtype=np.uint64)
_SLOT_SEEDS = np.random.default_rng(SEED + 1).integers(1, 1 << 63, SLOTS, dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


class _Words(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 100_000:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


def _kmers(words: np.ndarray) -> np.ndarray:
    """Hashes of occurrence-labelled k-mers, in text order."""
    k = min(K, len(words))
    n = len(words) - k + 1
    h = np.zeros(n, np.uint64)
    for i in range(k):
        h = _mix(h * _M2 + words[i : i + n] + np.uint64(i + 1))
    order = np.argsort(h, kind="stable")
    s = h[order]
    fresh = np.concatenate([[True], s[1:] != s[:-1]])
    if not fresh.all():
        at = np.arange(n)
        label = np.empty(n, np.uint64)
        label[order] = (at - np.maximum.accumulate(np.where(fresh, at, 0))).astype(np.uint64)
        h = _mix(h + label * _M1)
    return h


def _bands(kmers: np.ndarray) -> list[int]:
    h = _mix(kmers[None, :] ^ _SEEDS[:, None])
    if len(kmers) > LEAST:
        at = np.sort(np.argpartition(h, LEAST - 1, axis=1)[:, :LEAST], axis=1)
        h = np.take_along_axis(h, at, axis=1)
    key = _SEEDS.copy()
    for column in h.T:
        key = _mix(key * _M1 + column)
    return key.view(np.int64).tolist()


def _signature(kmers: np.ndarray) -> bytes:
    """A byte of the least of the k-mers under each of 64 hashes; two bytes agree about as often as k-mers are shared."""
    least = np.empty(SLOTS, np.uint64)
    for i in range(0, SLOTS, 8):
        least[i : i + 8] = _mix(kmers[None, :] ^ _SLOT_SEEDS[i : i + 8, None]).min(axis=1)
    return (least >> np.uint64(56)).astype(np.uint8).tobytes()


def edit_distance_within(a: np.ndarray, b: np.ndarray, most: int) -> bool:
    """Whether at most `most` word edits turn `a` into `b`: rows of the alignment table, inside the band."""
    if abs(len(a) - len(b)) > most:
        return False
    offs = np.arange(-most, most + 1)
    far = len(a) + len(b) + 1
    padded = np.concatenate([b, [0]])
    row = np.where((offs >= 0) & (offs <= len(b)), offs, far)
    for i in range(1, len(a) + 1):
        j = offs + i
        inside = (j >= 0) & (j <= len(b))
        same = padded[np.clip(j - 1, 0, len(b))] == a[i - 1]
        step = np.minimum(row + ~(same & (j >= 1)), np.append(row[1:], far) + 1)
        step[~inside] = far
        row = np.where(inside, np.minimum.accumulate(step - offs) + offs, far)
        if row.min() > most:
            return False
    return bool(row[len(b) - len(a) + most] <= most)


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Both similarities of two texts given as word hashes."""
    if min(len(a), len(b)) < K:
        return np.array_equal(a, b)
    return _alike(a, b, _kmers(a), _kmers(b))


def _alike(a: np.ndarray, b: np.ndarray, ka: np.ndarray, kb: np.ndarray) -> bool:
    shared, ia, ib = np.intersect1d(ka, kb, assume_unique=True, return_indices=True)
    if len(shared) < SIMILAR * (len(ka) + len(kb) - len(shared)):
        return False
    most = int((1 - SIMILAR) * max(len(a), len(b)) + 1e-9)
    order = np.argsort(ia)
    ia, ib = ia[order], ib[order]
    if (np.diff(ib) > 0).all() and (np.abs(ia - ib) <= most).all():
        # shared k-mers in one order are an alignment; between them lie the only edits
        ends_a, ends_b = np.concatenate([[0], ia, [len(a)]]), np.concatenate([[0], ib, [len(b)]])
        gap = np.maximum(np.diff(ends_a), np.diff(ends_b)) - 1
        gap[0] += 1
        if int(np.maximum(gap, 0).sum()) <= most:
            return True
    return edit_distance_within(a, b, most)


def _cell_links(words: list[np.ndarray], names: np.ndarray, groups: np.ndarray, side: np.ndarray | None) -> list[tuple[int, int]]:
    """Pairs of groups that link across: a spanning forest, from exact k-mer overlaps of every pair of the cell."""
    kmers = [_kmers(t) if len(t) >= K else np.zeros(0, np.uint64) for t in words]
    sizes = np.array([len(k) for k in kmers])
    owner = np.repeat(np.arange(len(words)), sizes)
    _, code, times = np.unique(np.concatenate(kmers), return_inverse=True, return_counts=True)
    many = times > 1
    column = np.cumsum(many) - 1
    held = many[code]
    owner, code = owner[held], column[code[held]]
    order = np.argsort(code, kind="stable")
    owner, code = owner[order], code[order]
    shared = np.zeros((len(words), len(words)), np.float64)
    width = 8192
    for low in range(0, int(many.sum()), width):
        a, b = np.searchsorted(code, [low, low + width])
        part = np.zeros((len(words), width), np.float32)
        part[owner[a:b], code[a:b] - low] = 1
        shared += part @ part.T
    close = np.triu((shared >= SIMILAR * (sizes[:, None] + sizes[None, :] - shared)) & (shared > 0), 1)
    close &= groups[:, None] != groups[None, :]
    if side is not None:
        close &= side[:, None] != side[None, :]
    root = groups.copy()
    out = []
    for i, j in np.argwhere(close).tolist():
        if root[i] != root[j] and _alike(words[i], words[j], kmers[i], kmers[j]):
            root[root == root[j]] = root[i]
            out.append((int(names[i]), int(names[j])))
    return out


def _may_link(marks: np.ndarray, sizes: np.ndarray, groups: np.ndarray, side: np.ndarray | None) -> np.ndarray:
    """Which texts of a cell have a partner of another group that they may link with."""
    out = np.zeros(len(marks), bool)
    for low in range(0, len(marks), 64):
        part = slice(low, low + 64)
        agree = (marks[part, None, :] == marks[None, :, :]).sum(axis=2) >= LIKELY
        agree &= groups[part, None] != groups[None, :]
        agree &= np.minimum(sizes[part, None], sizes[None, :]) >= SIMILAR * np.maximum(sizes[part, None], sizes[None, :])
        if side is not None:
            agree &= side[part, None] != side[None, :]
        out[part] |= agree.any(axis=1)
    return out


_CELL_KEY = ("key", "bi", "bj")


def _by_cell(take):
    """Runs `take(key, rows)` over the rows of each cell; a cell's rows stand together and may span batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        last = None

        def done(parts):
            rows = pa.Table.from_batches(parts).combine_chunks()
            return take(last, rows) if rows.num_rows > 1 else None

        for batch in batches:
            if not len(batch):
                continue
            keys = [batch.column(c).to_numpy(zero_copy_only=False) for c in _CELL_KEY]
            cuts = [0, *(np.flatnonzero(np.any([k[1:] != k[:-1] for k in keys], axis=0)) + 1).tolist(), len(batch)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                key = tuple(int(k[a]) for k in keys)
                if key != last and held:
                    got = done(held)
                    held = []
                    if got is not None:
                        yield got
                last = key
                held.append(batch.slice(a, b - a))
        if held:
            got = done(held)
            if got is not None:
                yield got

    return run


def _side(key: tuple, rows: pa.Table) -> np.ndarray | None:
    return rows.column("mine").to_numpy() != key[1] if key[1] != key[2] else None


def _screened(key: tuple, rows: pa.Table) -> pa.RecordBatch | None:
    marks = np.frombuffer(b"".join(rows.column("marks").to_pylist()), np.uint8).reshape(rows.num_rows, SLOTS)
    need = _may_link(marks, rows.column("size").to_numpy(), rows.column("grp").to_numpy(), _side(key, rows))
    if not need.any():
        return None
    return rows.filter(pa.array(need)).select([*_CELL_KEY, "rep", "half", "grp", "mine"]).combine_chunks().to_batches()[0]


def _joined_groups(key: tuple, rows: pa.Table) -> pa.RecordBatch | None:
    words = [np.frombuffer(w, np.uint32).astype(np.uint64) for w in rows.column("words").to_pylist()]
    groups = rows.column("grp").to_numpy()
    out = _cell_links(words, groups, groups, _side(key, rows))
    if not out:
        return None
    return pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], pa.int64()) for i in (0, 1)], names=["a", "b"])


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    table = _Words()
    for batch in batches:
        ids, prints, bands = [], [], []
        for i, t in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
            words = (t.as_py() or "").encode().split()
            if words:
                ids.append(i)
                prints.append(hashlib.md5(b" ".join(words)).digest())
                bands.append(_bands(_kmers(np.array([table[w] & 0xFFFFFFFF for w in words], np.uint64))))
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(prints, pa.binary()), pa.array(bands, pa.list_(pa.int64()))], names=["doc_id", "print", "bands"])


def _word_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    table = _Words()
    for batch in batches:
        out = []
        for i, t in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
            words = (t.as_py() or "").encode().split()
            if words:
                own = np.array([table[w] & 0xFFFFFFFF for w in words], np.uint32)
                kmers = _kmers(own.astype(np.uint64))
                half = int.from_bytes(hashlib.md5(b" ".join(words)).digest()[:8], "big", signed=True)
                out.append((i, half, own.tobytes(), _signature(kmers), len(kmers)))
        types = [pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.int32()]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(types)], names=["rep", "half", "words", "marks", "size"])


def _likely(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, SLOTS) for c in ("marks_a", "marks_b"))
        yield batch.filter(pa.array((x == y).sum(axis=1) >= LIKELY)).select(["rep_a", "half_a", "rep_b", "half_b"])


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ok = [similar(*(np.frombuffer(w.as_buffer(), np.uint32).astype(np.uint64) for w in pair)) for pair in zip(batch.column("words_a"), batch.column("words_b"), strict=True)]
        yield batch.select(["rep_a", "rep_b"]).filter(pa.array(ok, pa.bool_()))


def _of(table: DataFrame, side: str, *columns: str) -> DataFrame:
    """`columns` of the texts' table, named for one side of a pair; its keys are many, so it is never broadcast."""
    return table.select(*[F.col(c).alias(f"{c}_{side}") for c in ("rep", "half", *columns)]).hint("merge")


def _in_cells(rows: DataFrame, width: int) -> DataFrame:
    return rows.repartition(width, *_CELL_KEY).sortWithinPartitions(*_CELL_KEY, "rep", "half")


def _named(found: DataFrame, rows: DataFrame, column: str) -> DataFrame:
    """`rows` with `column` replaced by its component, itself where it has none."""
    labels = found.select(F.col("v").alias("__v"), "component")
    return rows.join(labels.hint("merge"), F.col(column) == F.col("__v"), "left").withColumn(column, F.coalesce("component", column)).drop("__v", "component")


def classes(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """doc_id, class_id, kept: one row for each row of `docs`."""
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    known = base.where("doc_id IS NOT NULL")
    sketched = written(spark, known.mapInArrow(trimmed(_sketch), "doc_id long, print binary, bands array<long>"), "omh-sketch")
    half = F.conv(F.hex(F.substring("print", 1, 8)), 16, -10).cast("long").alias("half")
    one = sketched.groupBy("print").agg(F.min("doc_id").alias("rep"), F.min("bands").alias("bands"))
    first = written(spark, one.select("print", "rep", half, "bands"), "omh-first")
    # a key holds its band by its seed
    entries = first.select("rep", "half", F.explode("bands").alias("key"))
    shared = entries.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    members = written(spark, entries.join(shared.select("key"), "key").distinct(), "omh-members")
    text = F.struct("rep", "half")
    alike = members.groupBy("key").agg(F.count("*").alias("n"), F.min(text).alias("lead"), F.bit_xor(F.xxhash64(text)).alias("x"), F.bit_xor(F.xxhash64(text, F.lit(1))).alias("y"))
    # buckets of the same texts under several keys are one bucket
    buckets = alike.groupBy("n", "lead", "x", "y").agg(F.min("key").alias("key")).where("n > 1").select("key", "n", "lead")
    placed = written(spark, members.join(buckets, "key"), "omh-placed")
    wanted = placed.select("rep", "half").distinct()
    ids = written(spark, wanted.select(F.col("rep").alias("doc_id")).distinct(), "omh-wanted")
    texts = known.join(sized(ids), "doc_id", "left_semi").mapInArrow(trimmed(_word_rows), "rep long, half long, words binary, marks binary, size int")
    words = written(spark, texts.dropDuplicates(["rep", "half"]), "omh-words")
    discard(spark, members)
    pairs = placed.where(text != F.col("lead")).select(F.col("lead.rep").alias("rep_a"), F.col("lead.half").alias("half_a"), F.col("rep").alias("rep_b"), F.col("half").alias("half_b")).distinct()
    sides = (["rep_a", "half_a"], ["rep_b", "half_b"])
    signed = pairs.join(_of(words, "a", "marks"), sides[0]).join(_of(words, "b", "marks"), sides[1])
    likely = written(spark, signed.select("rep_a", "half_a", "rep_b", "half_b", "marks_a", "marks_b").mapInArrow(trimmed(_likely), "rep_a long, half_a long, rep_b long, half_b long"), "omh-likely")
    loaded = likely.join(_of(words, "a", "words"), sides[0]).join(_of(words, "b", "words"), sides[1])
    linked = written(spark, loaded.select("rep_a", "rep_b", "words_a", "words_b").mapInArrow(trimmed(_verify), "rep_a long, rep_b long"), "omh-linked")
    discard(spark, likely)
    # groups so far: linked texts, and the texts of rows that share a doc_id
    copies = sketched.select("doc_id", "print").join(first.select("print", "rep").hint("merge"), "print").select("doc_id", "rep")
    several = copies.groupBy("doc_id").agg(F.min("rep").alias("a"), F.max("rep").alias("z"), F.collect_set("rep").alias("all")).where("a <> z")
    several = several.select("a", F.explode("all").alias("b")).where("a <> b")
    groups = components(spark, linked.select(F.col("rep_a").alias("a"), F.col("rep_b").alias("b")).unionByName(several))
    labelled = written(spark, _named(groups, placed.select("key", "n", "rep", "half", F.col("rep").alias("grp")), "grp"), "omh-groups")
    mixed = labelled.groupBy("key").agg(F.min("grp").alias("a"), F.max("grp").alias("z")).where("a <> z").select("key")
    rest = labelled.join(mixed, "key", "left_semi").where("n > 2").withColumn("blocks", F.ceil(F.col("n") / CELL).cast("int"))
    rest = rest.withColumn("mine", F.pmod(F.xxhash64("rep", "half"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rest = rest.select("key", "rep", "half", "grp", "mine", F.least("mine", "other").alias("bi"), F.greatest("mine", "other").alias("bj"))
    width = max(2, shuffle_width(spark))
    marked = rest.join(words.select("rep", "half", "marks", "size").hint("merge"), ["rep", "half"])
    cell = "key long, bi int, bj int, rep long, half long, grp long, mine int"
    needed = written(spark, _in_cells(marked.select(*_CELL_KEY, "rep", "half", "grp", "mine", "marks", "size"), width).mapInArrow(trimmed(_by_cell(_screened)), cell), "omh-needed")
    dealt = _in_cells(needed.join(words.select("rep", "half", "words").hint("merge"), ["rep", "half"]).select(*_CELL_KEY, "rep", "half", "grp", "mine", "words"), width)
    across = written(spark, dealt.mapInArrow(trimmed(_by_cell(_joined_groups)), "a long, b long"), "omh-across")
    joined = components(spark, across)
    out = written(spark, _named(joined, _named(groups, copies.select("doc_id", F.col("rep").alias("class_id")), "class_id"), "class_id").groupBy("doc_id").agg(F.min("class_id").alias("class_id")), "omh-classes")
    for done in (ids, placed, words, linked, labelled, needed, across, first, sketched, groups, joined):
        discard(spark, done)
    named = base.select("doc_id").join(out.hint("merge"), "doc_id", "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"))
    return named.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("class_id"), F.lit(True)))


def drop_copies(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """`docs` with one row of each class: its least doc_id, and of rows that share that doc_id the least as JSON.

    Rows with a null doc_id stay.
    """
    found = classes(spark, docs).where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("kept").alias("kept"), F.count("*").alias("n"))
    found = written(spark, found.where("NOT kept OR n > 1").select(F.col("doc_id").alias("__near_id"), "kept"), "omh-gone")
    stay = docs.join(sized(found), F.col("doc_id").cast("long") == F.col("__near_id"), "left_anti")
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    again = docs.select(F.col("doc_id").cast("long").alias("__near_id"), whole.alias("__near_row")).join(sized(found.where("kept")), "__near_id", "left_semi")
    again = again.groupBy("__near_id").agg(F.min_by("__near_row", F.to_json("__near_row")).alias("__near_row")).select("__near_row.*")
    return stay.unionByName(again)
