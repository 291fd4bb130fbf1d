"""Reads a byte-level BPE vocabulary (tokenizers' JSON form) into arrays; nothing here trains or encodes."""

from __future__ import annotations

import functools
import json

import numpy as np

END = 256  # a symbol is a byte, plus END where it closes a word of a vocabulary with word ends


def byte_letters() -> list[str]:
    """The printable stand-in of each byte: itself where Latin-1 prints it, else the next letter from U+0100 on."""
    out, spare = [], 256
    for b in range(256):
        if 0x21 <= b <= 0x7E or 0xA1 <= b <= 0xAC or 0xAE <= b <= 0xFF:
            out.append(chr(b))
        else:
            out.append(chr(spare))
            spare += 1
    return out


class Vocabulary:
    """Tokens as symbol tuples, merges in priority order as id triples, special tokens apart."""

    def __init__(self, spec: dict):
        model = spec["model"]
        ids: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.labels = [""] * (max([*ids.values(), *self.special.values()]) + 1)
        for label, i in (ids | self.special).items():
            self.labels[i] = label
        value = {letter: b for b, letter in enumerate(byte_letters())}
        self.symbols: dict[int, tuple[int, ...]] = {}
        for label, i in ids.items():
            body = label[: -len(self.suffix)] if self.suffix and label.endswith(self.suffix) and label != self.suffix else label
            if label in self.special or any(c not in value for c in body):
                continue
            syms = [value[c] for c in body]
            if body is not label:
                syms[-1] += END
            self.symbols[i] = tuple(syms)
        # a pair is text "left right" in older files and a list of two in newer ones
        pairs = (m.split(" ") if isinstance(m, str) else m for m in model["merges"])
        self.merges = np.array([(ids[a], ids[b], ids[self._joined(a, b)]) for a, b in pairs], np.int64).reshape(-1, 3)

    def _joined(self, left: str, right: str) -> str:
        return left + right


@functools.cache
def vocabulary(path: str) -> Vocabulary:
    with open(path, encoding="utf-8") as f:
        return Vocabulary(json.load(f))


@functools.cache
def library_tokenizer(path: str):
    """The library's tokenizer without truncation and padding, one thread a task."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    t.no_truncation()
    t.no_padding()
    return t


@functools.cache
def library_splitter(path: str):
    """The library's normalizer and splitter alone, without the tokens and merges that it would hold beside them."""
    from tokenizers import Tokenizer

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    spec["model"] |= {"vocab": {}, "merges": []}
    return Tokenizer.from_str(json.dumps(spec | {"added_tokens": [], "truncation": None, "padding": None}))
