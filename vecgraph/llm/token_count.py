"""Token counts by rank-synchronous merging of ragged arrays.

The distinct pre-tokens of a batch lie one after the other in one array of
symbols with the offsets of each. In every round each pre-token finds the lowest
rank among its neighbouring pairs and merges all occurrences of that pair, left
to right, at once with all others; the rounds end when no pre-token has a pair
to merge. What survives is counted.

Counts of pre-tokens seen before are kept in a table of bounded size, which is
emptied when full; no text is cut or skipped.

Cases: a null text is empty and has no tokens. A special string inside a text
is one token, as the tokenizers library has it. Very long pre-tokens take time
and memory in proportion to their length. Repeated rows each get a row; a null
doc_id stays null; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_texts
from .vocabulary import Vocabulary, load, locate

#: Pre-tokens whose count a worker remembers.
REMEMBERED = 300_000
LIMIT = 512
ROUNDS = 48
_NEVER = np.int64(1) << 40


class RankMerger:
    """Counts surviving symbols of pre-tokens."""

    def __init__(self, vocabulary: Vocabulary):
        pairs = np.array([(a << 32 | b, rank, made) for (a, b), (rank, made) in vocabulary.merges.items()], dtype=np.int64).reshape(-1, 3)
        pairs = pairs[np.argsort(pairs[:, 0])]
        self.keys, self.ranks, self.made = (np.ascontiguousarray(pairs[:, k]) for k in range(3))
        self.base = vocabulary.base

    def count(self, words: list[bytes]) -> np.ndarray:
        """Symbols that survive in each of the words (none of them empty)."""
        sizes = np.array([len(w) for w in words], dtype=np.int64)
        symbols = self.base[np.frombuffer(b"".join(words), dtype=np.uint8)]
        owner = np.repeat(np.arange(len(words)), sizes)
        counts = sizes.copy()
        done = 0
        while len(symbols) > 1:
            if done == ROUNDS:
                self._merge_by_rank(symbols, owner, counts)
                break
            done += 1
            inside = owner[:-1] == owner[1:]
            key = symbols[:-1] << 32 | symbols[1:]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            rank = np.where(inside & (self.keys[at] == key), self.ranks[at], _NEVER)
            starts = np.flatnonzero(np.concatenate([[True], owner[:-1] != owner[1:]]))
            least = np.minimum.reduceat(np.append(rank, _NEVER), starts)
            merging = least < _NEVER
            if not merging.any():
                break
            lengths = np.diff(np.append(starts, len(symbols)))
            chosen = (rank == np.repeat(least, lengths)[:-1]) & (rank < _NEVER)
            # A pair that overlaps the one before it (as in a run of one symbol) only merges at every second place.
            place = np.arange(len(chosen))
            first = chosen & ~np.concatenate([[False], chosen[:-1]])
            run = np.maximum.accumulate(np.where(first, place, 0))
            chosen &= (place - run) % 2 == 0
            hits = np.flatnonzero(chosen)
            symbols[hits] = self.made[at[hits]]
            counts -= np.bincount(owner[hits], minlength=len(words))
            keep = np.ones(len(symbols), dtype=bool)
            keep[hits + 1] = False
            # Words without a further pair leave the array.
            keep &= np.repeat(merging, lengths)
            symbols, owner = symbols[keep], owner[keep]
        return counts

    def _merge_by_rank(self, symbols: np.ndarray, owner: np.ndarray, counts: np.ndarray) -> None:
        """Merge what is left, rank by rank; each removed symbol is taken off its word's count."""
        n = len(symbols)
        after, before, alive = np.arange(1, n + 1), np.arange(-1, n - 1), np.ones(n, dtype=bool)
        waiting: dict[int, list[np.ndarray]] = {}
        ranks: list[int] = []

        def pairs(left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """Rank of the pair that begins at each place, and its place in the table."""
            right = np.minimum(after[left], n - 1)
            key = symbols[left] << 32 | symbols[right]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            return np.where((after[left] < n) & (owner[left] == owner[right]) & (self.keys[at] == key), self.ranks[at], _NEVER), at

        def wait(left: np.ndarray) -> None:
            rank, _ = pairs(left)
            left, rank = left[rank < _NEVER], rank[rank < _NEVER]
            order = np.argsort(rank, kind="stable")
            left, rank = left[order], rank[order]
            cuts = np.flatnonzero(rank[1:] != rank[:-1]) + 1
            for r, part in zip(rank[np.concatenate([[0], cuts])].tolist() if len(rank) else (), np.split(left, cuts)):
                if r not in waiting:
                    waiting[r] = []
                    heapq.heappush(ranks, r)
                waiting[r].append(part)

        wait(np.arange(n))
        while ranks:
            r = heapq.heappop(ranks)
            left = np.unique(np.concatenate(waiting.pop(r)))
            left = left[alive[left]]
            rank, at = pairs(left)
            left, at = left[rank == r], at[rank == r]
            if not len(left):
                continue
            right = after[left]
            # In a run of overlapping pairs every second one merges.
            place = np.arange(len(left))
            first = np.concatenate([[True], left[1:] != right[:-1]])
            keep = (place - np.maximum.accumulate(np.where(first, place, 0))) % 2 == 0
            left, right, at = left[keep], right[keep], at[keep]
            symbols[left], alive[right] = self.made[at], False
            after[left] = after[right]
            inner = after[left] < n
            before[after[left][inner]] = left[inner]
            np.subtract.at(counts, owner[left], 1)
            wait(np.unique(np.concatenate([left, before[left][before[left] >= 0]])))


_MERGERS: dict[str, tuple[RankMerger, dict[str, int]]] = {}


def count_texts(texts: list[str], path: str) -> list[int]:
    """Tokens of each text."""
    vocabulary = load(path)
    if path not in _MERGERS:
        _MERGERS[path] = (RankMerger(vocabulary), {})
    merger, known = _MERGERS[path]
    if len(known) > REMEMBERED:
        known.clear()
    if not known:
        known.update(dict.fromkeys(vocabulary.specials, 1))
    out = []
    # A group's pre-tokens are merged together; a group ends by size, so that memory stays bounded.
    group, weight = [], 0
    for k, text in enumerate(texts):
        group.append(vocabulary.split(text))
        weight += len(text)
        if weight > 1_000_000 or k == len(texts) - 1:
            new = list({p for pieces in group for p in pieces if p not in known})
            if new:
                known.update(zip(new, merger.count([p.encode("utf-8") for p in new]).tolist()))
            out += [sum(map(known.__getitem__, pieces)) for pieces in group]
            group, weight = [], 0
            if len(known) > 2 * REMEMBERED:
                known.clear()
                known.update(dict.fromkeys(vocabulary.specials, 1))
    return out


def token_counts(docs: DataFrame, path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit: one row for each row of ``docs``."""

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [t or "" for t in batch.column(1).to_pylist()]
        counts = np.array(count_texts(texts, locate(path)), dtype=np.int64)
        sizes = np.array([len(t.encode("utf-8")) for t in texts], dtype=np.int64)
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes), pa.array(counts), pa.array(counts > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return map_texts(docs, ["doc_id", "text"], work, "doc_id bigint, n_bytes bigint, n_tokens bigint, over_limit boolean")
