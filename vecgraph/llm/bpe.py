"""BPE encoding by backtracking over longest matches, and decoding by an offset table.

An Aho-Corasick automaton over all tokens finds in one pass the tokens that
start at each place of a pre-token. The encoder takes the longest one that may
follow the token before it; where none may, the place is dead (the token that
ends there is unique) and the encoder goes back one token to its next shorter
choice. Two tokens may be neighbours exactly if BPE never merges across their
border: of the tokens that stand left and right of the border while both are
built, no two that stand there at the same time have a merge that comes before
either is built on. The answers are kept in a table of pairs.

Encodings of pre-tokens seen before are kept in a table of bounded size. No
text is cut.

Decoding looks up each id's bytes in one array by its offset.

Cases: a null text is empty: no ids, and an empty string decoded. A special
string inside a text is one token. Repeated rows each get a row; a null doc_id
stays null; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_texts
from .vocabulary import Vocabulary, load, locate

#: Pre-tokens (in each of two generations) and pairs that a worker remembers.
REMEMBERED = 200_000
_LAST = 1 << 60


class _Encodings(dict):
    """Encodings of pre-tokens, made when they are first asked for; what the generation before has moves on."""

    def __init__(self, make, before: dict):
        self.make, self.before = make, before

    def __missing__(self, piece: str) -> tuple[str, bytes]:
        found = self.before.get(piece)
        if found is None:
            ids = self.make(piece)
            found = (",".join(map(str, ids)), array("i", ids).tobytes())
        self[piece] = found
        return found


class Encoder:
    """Exact BPE of pre-tokens by backtracking."""

    def __init__(self, vocabulary: Vocabulary):
        import ahocorasick

        self.vocabulary = vocabulary
        self.merges = vocabulary.merges
        # How each token is made: (rank, left, right); the first merge that makes it counts.
        self.made: dict[int, tuple[int, int, int]] = {}
        for (left, right), (rank, token) in vocabulary.merges.items():
            self.made.setdefault(token, (rank, left, right))
        self.automaton = ahocorasick.Automaton()
        self.matches: dict[str, tuple[int, int, str]] = {}
        for token, i in vocabulary.tokens.items():
            if token not in vocabulary.specials:
                self.matches[token] = (len(token), i, token)
                self.automaton.add_word(token, self.matches[token])
        self.automaton.make_automaton()
        self.shorter: dict[str, tuple[int, int, str] | None] = {}
        self.pairs: dict[tuple[int, int], bool] = {}
        self.known = _Encodings(self.encode_piece, {})

    def _edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """Tokens that stand at the token's right (2) or left (1) end while it is built, each with the rank at which it is built on."""
        out, until = [], _LAST
        while True:
            out.append((token, until))
            if token not in self.made:
                return out
            until = self.made[token][0]
            token = self.made[token][side]

    def compatible(self, a: int, b: int) -> bool:
        """Whether BPE leaves a border between tokens a and b."""
        found = self.pairs.get((a, b))
        if found is None:
            found = True
            right = self._edge(b, 1)
            for x, x_until in self._edge(a, 2):
                for y, y_until in right:
                    merge = self.merges.get((x, y))
                    # Of equal ranks the leftmost pair merges first.
                    if merge is not None and merge[0] < x_until and merge[0] <= y_until:
                        found = False
            if len(self.pairs) > REMEMBERED:
                self.pairs.clear()
            self.pairs[a, b] = found
        return found

    def next_shorter(self, token: str) -> tuple[int, int, str] | None:
        """The longest token that opens this one."""
        if token not in self.shorter:
            self.shorter[token] = next((self.matches[token[:k]] for k in range(len(token) - 1, 0, -1) if token[:k] in self.matches), None)
        return self.shorter[token]

    def encode_piece(self, piece: str) -> list[int]:
        special = self.vocabulary.specials.get(piece)
        if special is not None:
            return [special]
        word = "".join(map(self.vocabulary.to_alphabet.__getitem__, piece.encode("utf-8")))
        n = len(word)
        # The longest token at each place: the automaton reports longer ones later.
        longest: list = [None] * (n + 1)
        for end, match in self.automaton.iter(word):
            longest[end + 1 - match[0]] = match
        dead = bytearray(n + 1)
        ids: list[int] = []
        chosen: list[tuple[int, int, str]] = []
        pairs, last, at, match = self.pairs, -1, 0, longest[0]
        while at < n:
            while match is not None:
                size, token, text = match
                if not dead[at + size]:
                    fits = last < 0 or pairs.get((last, token))
                    if fits is None:
                        fits = self.compatible(last, token)
                    if fits:
                        break
                match = self.next_shorter(text)
            if match is not None:
                ids.append(token)
                chosen.append(match)
                last = token
                at += size
                match = longest[at]
            else:
                dead[at] = 1
                if not ids:
                    raise ValueError("the vocabulary has no encoding for a piece")
                ids.pop()
                size, token, text = chosen.pop()
                last = ids[-1] if ids else -1
                at -= size
                match = self.next_shorter(text)
        return ids

    def encode(self, text: str) -> tuple[str, np.ndarray]:
        """The ids of a text, as decimals joined by commas and as an array."""
        if len(self.known) > REMEMBERED:
            self.known = _Encodings(self.encode_piece, dict(self.known))
        found = list(map(self.known.__getitem__, self.vocabulary.split(text)))
        return ",".join([f[0] for f in found]), np.frombuffer(b"".join([f[1] for f in found]), dtype=np.int32)

    def decode(self, ids: np.ndarray) -> str:
        offsets = self.vocabulary.offsets
        begins = offsets[ids]
        sizes = offsets[ids.astype(np.int64) + 1] - begins
        ends = np.cumsum(sizes)
        total = int(ends[-1]) if len(ends) else 0
        places = np.repeat(begins - (ends - sizes), sizes) + np.arange(total)
        return self.vocabulary.blob[places].tobytes().decode("utf-8", "replace")


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(load(path))
    return _ENCODERS[path]


def encoded(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids (array of int), decoded: one row for each row of ``docs``."""

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        own = encoder(locate(path))
        ids = [own.encode(t or "")[1] for t in batch.column(1).to_pylist()]
        return pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(ids, type=pa.list_(pa.int32())), pa.array([own.decode(i) for i in ids])], ["doc_id", "ids", "decoded"]
        )

    return map_texts(docs, ["doc_id", "text"], work, "doc_id bigint, ids array<int>, decoded string", rows=128)


def encoding_report(docs: DataFrame, path: str | None = None, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids, if asked for): one row for each row of ``docs``."""

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        own = encoder(locate(path))
        counts, shown, back, kept = [], [], [], []
        for t in batch.column(1).to_pylist():
            text, ids = own.encode(t or "")
            counts.append(len(ids))
            shown.append(hashlib.sha256(text.encode("ascii")).hexdigest())
            back.append(hashlib.sha256(own.decode(ids).encode("utf-8")).hexdigest())
            kept.append(ids)
        columns = [batch.column(0), pa.array(counts, type=pa.int64()), pa.array(shown), pa.array(back)]
        names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
        if with_ids:
            columns, names = [*columns, pa.array(kept, type=pa.list_(pa.int32()))], [*names, "ids"]
        return pa.RecordBatch.from_arrays(columns, names)

    schema = "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return map_texts(docs, ["doc_id", "text"], work, schema, rows=128 if with_ids else 512)
