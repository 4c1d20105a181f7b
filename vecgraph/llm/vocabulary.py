"""A byte-level BPE vocabulary read from a tokenizer's JSON file, shared by the encoder and the counter.

The file is a parameter. Each Python worker reads it once and keeps it.
"""

from __future__ import annotations

import json
from functools import lru_cache

import numpy as np

DEFAULT = "byte_bpe_50k.json"


def locate(path: str | None) -> str:
    """The given path, or the default public vocabulary's place on this machine."""
    if path is not None:
        return path
    import public_tokenizers

    return public_tokenizers.path(DEFAULT)


def byte_alphabet() -> list[str]:
    """The printable stand-in of each byte: itself if printable and no blank, else the next free character from U+0100 on."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    free = iter(range(0x100, 0x200))
    return [chr(b) if b in printable else chr(next(free)) for b in range(256)]


class Vocabulary:
    """Token ids, merges and special strings of one file."""

    def __init__(self, path: str):
        import public_tokenizers
        import regex

        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        vocab = data["model"]["vocab"]
        alphabet = byte_alphabet()
        self.tokens: dict[str, int] = vocab
        self.base = np.array([vocab[c] for c in alphabet], dtype=np.int64)
        self.to_alphabet = {b: c for b, c in enumerate(alphabet)}
        #: (left, right) -> (rank, merged id), in order of rank
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, m in enumerate(data["model"]["merges"]):
            left, right = m.split(" ") if isinstance(m, str) else m
            self.merges[vocab[left], vocab[right]] = (rank, vocab[left + right])
        self.specials = {t["content"]: t["id"] for t in data.get("added_tokens", [])}
        longest_first = sorted(self.specials, key=len, reverse=True)
        self._special = regex.compile("(" + "|".join(map(regex.escape, longest_first)) + ")") if longest_first else None
        self._pieces = regex.compile(public_tokenizers.PATTERN).findall
        back = {c: b for b, c in enumerate(alphabet)}
        by_id: list[bytes] = [b""] * (1 + max([*vocab.values(), *self.specials.values()]))
        for token, i in vocab.items():
            by_id[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
        for token, i in self.specials.items():
            by_id[i] = token.encode()
        #: The bytes of all tokens one after the other, and where each begins.
        self.blob = np.frombuffer(b"".join(by_id), dtype=np.uint8)
        self.offsets = np.concatenate([[0], np.cumsum([len(x) for x in by_id])]).astype(np.int64)

    def split(self, text: str) -> list[str]:
        """Pre-tokens in order; a special string is a piece of its own."""
        if self._special is None or not any(s in text for s in self.specials):
            return self._pieces(text)
        out: list[str] = []
        for k, part in enumerate(self._special.split(text)):
            if k % 2:
                out.append(part)
            else:
                out += self._pieces(part)
        return out


@lru_cache(maxsize=4)
def load(path: str) -> Vocabulary:
    return Vocabulary(path)
