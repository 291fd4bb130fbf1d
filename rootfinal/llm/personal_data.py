"""Personal data: patterns propose, checksums confirm, context words adjust a score.

Base kinds are email, ip, card (Luhn) and phone. The method adds account numbers (iban, mod-97) and, where a
nearby context word lifts their score over the threshold, identity numbers (nnn-nn-nnnn). Base spans always stay, and the
score of every span, raised by context words beside it, stands in `scores`. Offsets are code points, ends exclusive.

Null and empty texts have no spans; texts of any length are searched whole. Spans that start together stand in the order of their
kinds. Rows, also repeated ones, are independent; an empty table gives no rows. A kept column named like an output gets `_in` behind its name.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import carried

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "iban", "idnum")
# fixed values: words that make a span near them likelier
CONTEXT = {
    "email": ("mail", "email", "e-mail", "contact"), "ip": ("ip", "address", "host", "server"),
    "card": ("card", "visa", "credit", "payment"), "phone": ("phone", "call", "tel", "mobile"),
    "iban": ("iban", "account", "bank"), "idnum": ("ssn", "social", "security", "identity", "id"),
}
SCORE = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.6, "iban": 0.8, "idnum": 0.3}
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# a match never starts inside a run of digits: it would have started at the run's first one
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"(?<![0-9])[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?= ?[A-Z0-9])")
# fixed values: characters of an account number by country
_IBAN_SIZE = {
    c: int(n)
    for n, names in (x.split(":") for x in (
        "15:NO", "16:BE", "18:DK FI FK FO GL NL SD", "19:MK SI", "20:AT BA EE KZ LT LU MN XK", "21:CH HR LI LV", "22:BG BH CR DE GB GE IE ME RS VA",
        "23:AE GI IL IQ OM SO TL", "24:AD CZ ES MD PK RO SA SE SK TN VG", "25:LY PT ST", "26:IS TR", "27:BI DJ FR GR IT MC MR SM",
        "28:AL AZ BY CY DO GT HN HU LB NI PL SV", "29:BR EG PS QA UA", "30:JO KW MU YE", "31:MT SC", "32:LC", "33:RU",
    ))
    for c in names.split()
}
_IBAN_OF_SIZE = {n: re.compile(r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){%d}(?![A-Za-z0-9])" % (n - 4)) for n in range(15, 35)}
_IDNUM = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_WORD = re.compile(r"[a-z-]+")


def luhn(digits: str) -> bool:
    odd = [int(c) for c in digits[-1::-2]]
    even = [2 * int(c) for c in digits[-2::-2]]
    return (sum(odd) + sum(d - 9 if d > 9 else d for d in even)) % 10 == 0


def mod97(code: str) -> bool:
    plain = code.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1


def _digits(s: str) -> str:
    return "".join(c for c in s if c in "0123456789")


def _emails(text: str) -> Iterator[tuple[int, int]]:
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at) if start < at else None
        if m:
            done = m.end()
            yield start, done
        else:
            done = max(done, at)
        at = text.find("@", max(at + 1, done))


def _ibans(text: str) -> Iterator[tuple[int, int]]:
    """A country's numbers have one size; of any other code the longest end that mod-97 confirms."""
    done = 0
    for m in _IBAN.finditer(text):
        a = m.start()
        if a < done:
            continue
        size = _IBAN_SIZE.get(text[a : a + 2])
        for n in (size,) if size else range(34, 14, -1):
            whole = _IBAN_OF_SIZE[n].match(text, a)
            if whole and mod97(whole.group()):
                done = whole.end()
                yield a, done
                break


def find_spans(text: str, threshold: float = 0.5, reach: int = 40) -> list[tuple[str, int, int, float]]:
    """(kind, start, end, score) by start, then kind as listed in KINDS."""
    found = [("email", a, b) for a, b in _emails(text)] if "@" in text else []
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split(".")):
            found.append(("ip", *m.span()))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 12:
            d = _digits(m.group())
            if 12 <= len(d) <= 19 and luhn(d):
                found.append(("card", *m.span()))
    if "+" in text:
        found.extend(("phone", *m.span()) for m in _PHONE.finditer(text) if 9 <= len(_digits(m.group())) <= 15)
    found.extend(("iban", a, b) for a, b in _ibans(text))
    found.extend(("idnum", *m.span()) for m in _IDNUM.finditer(text))
    out = []
    for kind, a, b in found:
        near = _WORD.findall((text[max(0, a - reach) : a] + " " + text[b : b + reach]).lower())
        score = min(1.0, SCORE[kind] + 0.3 * any(w in CONTEXT[kind] for w in near))
        if kind in BASE or score >= threshold:
            out.append((kind, a, b, score))
    return sorted(out, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


def redact(text: str, spans: list[tuple[str, int, int, float]]) -> str:
    """Each span replaced by its kind in angle brackets; overlapping spans merge under the first kind."""
    out, done, end = [], 0, -1
    for kind, a, b, _ in spans:
        if a < end:
            end = max(end, b)
            done = end
            continue
        out += [text[done:a], f"<{kind}>"]
        done = end = b
    return "".join(out) + text[done:]


def _joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b, _ in spans)


def span_table(df: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    extra = [*(T.StructField(f"n_{k}", T.LongType()) for k in BASE), *(T.StructField(c, T.StringType()) for c in ("base_sha256", "spans")), T.StructField("scores", T.ArrayType(T.DoubleType()))]
    base = df.select(*carried(keep, [f.name for f in extra]), F.col(text).alias("__text"))
    schema = T.StructType([*base.schema.fields[:-1], *extra])

    def run(batches):
        for batch in batches:
            rows = []
            for t in batch.column("__text"):
                spans = find_spans(t.as_py() or "")
                own = [s for s in spans if s[0] in BASE]
                rows.append((*(sum(s[0] == k for s in own) for k in BASE), hashlib.sha256(_joined(own).encode()).hexdigest(), _joined(spans), [s[3] for s in spans]))
            columns = zip(*rows, strict=True) if rows else [[]] * 7
            types = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.list_(pa.float64())]
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in range(len(keep))], *[pa.array(c, t) for c, t in zip(columns, types, strict=True)]], names=[f.name for f in schema])

    return base.mapInArrow(run, schema)


def redact_column(df: DataFrame, text: str = "text") -> DataFrame:
    """`df` with its text redacted; a null text stays null."""
    place = df.columns.index(text)

    def run(batches):
        for batch in batches:
            new = [None if t is None else redact(t, find_spans(t)) for t in (x.as_py() for x in batch.column(place))]
            yield batch.set_column(place, batch.schema.field(place), pa.array(new, batch.column(place).type))

    return df.mapInArrow(run, df.schema)
