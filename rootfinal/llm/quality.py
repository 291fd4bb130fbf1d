"""Rule bitmask ledger: every rule is evaluated once, its failure is a bit, its measurement stays beside it.

A versioned policy is a mask of rules that reject. Verdicts and ablations are bit operations on the ledger; no text
is read again. A null or empty text has no words, so it fails the base rules; a text of any length is measured whole. Words are runs
without ASCII white space. Rows, also repeated ones, are judged alone, so ties cannot occur; an empty table gives no rows.
A kept column named like an output gets `_in` behind its name.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import carried

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_distinct", "n_upper", "n_block_distinct")
BLOCK = 2000  # words
# rule -> condition on the measures under which a text fails; the position is the bit
RULES = {
    "few_words": "n_words < 50",
    "repeated_windows": "100 * n_repeat_words > 50 * n_words",
    "symbols": "10 * n_symbols > 2 * n_words",
    "dup_lines": "n_lines > 3 AND 100 * n_dup_lines > 40 * n_lines",
    "word_length": "word_chars < 2 * n_words OR word_chars > 12 * n_words",
    "few_distinct": "100 * n_block_distinct < 30 * n_words",
    "shouting": "2 * n_upper > word_chars",
}
BASE_MASK = 0b11
OUTPUTS = [*MEASURES, "failed_bits", "base_failed", "kept"]
POLICIES = {1: BASE_MASK, 2: (1 << len(RULES)) - 1}


def _block_distinct(words: list[bytes]) -> int:
    """Distinct words of consecutive blocks, summed; words left over count by the share of the last BLOCK words."""
    n = len(words)
    if n <= BLOCK:
        return len(set(words))
    left = n % BLOCK
    return sum(len(set(words[i : i + BLOCK])) for i in range(0, n - left, BLOCK)) + len(set(words[-BLOCK:])) * left // BLOCK


def measure(text: str) -> tuple[int, ...]:
    words = text.encode().split()
    n = len(words)
    if not n:
        return (0,) * len(MEASURES)
    chars = len(text) - sum(map(text.count, " \t\n\r\v\f"))
    symbols = sum(map(text.count, "#*$%&|<>"))
    lines = [x for x in text.split("\n") if x.strip(" \t\r\v\f")]
    repeated = 0
    if n >= 3:
        windows = list(zip(words, words[1:], words[2:], strict=False))
        if len(set(windows)) < len(windows):
            times, upto = Counter(windows), 0
            for i, w in enumerate(windows):
                if times[w] > 1:
                    repeated += i + 3 - max(i, upto)
                    upto = i + 3
    return n, chars, symbols, len(lines) - len(set(lines)), repeated, len(lines), len(set(words)), sum(map(str.isupper, text)), _block_distinct(words)


def ledger(df: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """`keep`, the measures and `failed_bits`."""
    base = df.select(*carried(keep, OUTPUTS), F.col(text).alias("__text"))
    schema = T.StructType([*base.schema.fields[:-1], *(T.StructField(m, T.LongType()) for m in MEASURES)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [measure(t.as_py() or "") for t in batch.column("__text")]
            columns = list(zip(*rows, strict=True)) or [[]] * len(MEASURES)
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in range(len(keep))], *[pa.array(c, pa.int64()) for c in columns]], names=[f.name for f in schema])

    bits = " + ".join(f"CASE WHEN {rule} THEN {1 << i} ELSE 0 END" for i, rule in enumerate(RULES.values()))
    return base.mapInArrow(run, schema).withColumn("failed_bits", F.expr(bits).cast("long"))


def apply_policy(rows: DataFrame, version: int = 2) -> DataFrame:
    mask = POLICIES[version]
    return rows.withColumn("base_failed", F.col("failed_bits").bitwiseAND(BASE_MASK) != 0).withColumn("kept", F.col("failed_bits").bitwiseAND(mask | BASE_MASK) == 0)


def good(docs: DataFrame, version: int = 2) -> DataFrame:
    """The rows of `docs` that a policy keeps, with their own columns."""
    rows = apply_policy(ledger(docs, docs.columns), version).where("kept")
    return rows.select(*[f"`{c}`" for c in rows.columns[: len(docs.columns)]]).toDF(*docs.columns)


def ablations(rows: DataFrame, version: int = 2) -> DataFrame:
    """For each rule of the policy: texts it fails, and texts that only it fails."""
    mask = POLICIES[version] | BASE_MASK
    hit = F.col("failed_bits").bitwiseAND(mask)
    stats = [F.struct(F.lit(name).alias("rule"), F.count_if(hit.bitwiseAND(1 << i) != 0).alias("n_failed"), F.count_if(hit == (1 << i)).alias("n_alone")) for i, name in enumerate(RULES)]
    return rows.agg(F.array(*stats).alias("r")).select(F.inline("r"))
