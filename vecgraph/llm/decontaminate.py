"""Benchmark decontamination: CGK embedding, bit sampling, exact verification.

Texts become sequences of 64-bit word hashes (letters and digits of any script,
lower case; everything else separates). A document is contaminated by an item
if some stretch of it is within ``floor(0.2 * words)`` word edits of the item,
a similarity of 0.8 or more.

1. Count filter. An edit spoils at most two neighbouring pairs of words, so a
   window of an item's size that is close to the item keeps all of the item's
   distinct pairs but two for each edit, and a shorter window one less for each
   word. Prefix sums over a table of pair flags (a pair that repeats within two
   places counts once, so two more may be missing) leave the documents and sizes
   that can match at all. Of any 2 * edits + 1 distinct pairs of an item one
   stays, so its rarest ones find the items to ask about; the exact number of
   the item's distinct pairs in each item-sized window leaves the windows. This
   loses nothing.
2. Embedding. Each window and each item walk their words: at step j the word at
   hand is written down, and a bit hashed from it and j says whether to move on.
   Sequences within a small edit distance then agree in most places (CGK maps
   edit to Hamming distance).
3. Sampling. Several walks, each with many small sets of places; a window meets
   the items of its size with which it agrees on some set. Walks are repeated
   until pairs at the edit limit, simulated for the largest item, meet with the
   target recall (``RECALL``).
4. Verification by the edit distance of the item to the best stretch around the
   window. With ``complete`` the windows of items that the sampling has not shown
   to be whole in the text are verified as well, so the result is exact; without
   it the result is what the sampling meets.

Items with fewer than five words allow no edit and are found as sequences of
words. Items beyond ``BLOCK`` (or ``BLOCK_BYTES`` of text) are taken in blocks,
each with its own pass; a block is broadcast once.

Cases: null texts, of documents or items, have no words and match nothing. A
null doc_id is carried as null. Repeated rows each get their rows; empty tables
give an empty result. Long texts are read whole.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, functions as F

from .common import map_texts

MIN_WORDS = 5
#: Word edits allowed, in fifths of an item's words: similarity 0.8.
EDIT_SHARE = 0.2
#: Sets of places in each walk, places in a set, and the most walks.
SETS, SAMPLED, MOST_WALKS = 16, 2, 16
#: Share of the pairs at the edit limit that the sampling is to meet.
RECALL = 0.97
#: Items, and bytes of their texts, that a worker holds at once.
BLOCK = 20_000
BLOCK_BYTES = 32 << 20
#: Bytes of text whose words are hashed at once.
CHUNK = 1 << 20
_FLAGS = 22
_ODD = 0x9E3779B97F4A7C15
_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
_U = np.uint64
_powers = (np.ones(1, dtype=_U), np.ones(1, dtype=_U))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(31))) * _U(0x7FB5D329728EA185)
    x = (x ^ (x >> _U(27))) * _U(0x81DADEF4BC2DD44D)
    return x ^ (x >> _U(33))


def _powers_up_to(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if len(_powers[0]) < n:
        size = 1 << (n - 1).bit_length()
        p, q = np.full(size, _ODD, dtype=_U), np.full(size, pow(_ODD, -1, 1 << 64), dtype=_U)
        p[0] = q[0] = 1
        _powers = (np.multiply.accumulate(p), np.multiply.accumulate(q))
    return _powers


def word_hashes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of all words of the texts, and where each text's words begin (one entry more than texts)."""
    raw = [t.lower().encode("utf-8", "surrogatepass") for t in texts]
    joined = b" ".join(raw).translate(_TABLE)
    at = np.frombuffer(joined, dtype=np.uint8)
    n = len(at)
    if n == 0:
        return np.zeros(0, dtype=_U), np.zeros(len(texts) + 1, dtype=np.int64)
    inside = np.zeros(n + 2, dtype=np.int8)
    inside[1:-1] = at != 32
    edge = np.diff(inside)
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    p, q = _powers_up_to(n)
    sums = np.zeros(n + 1, dtype=_U)
    np.cumsum(at * p[:n], out=sums[1:])
    words = _mix((sums[ends] - sums[starts]) * q[starts])
    offsets = np.cumsum([0] + [len(r) + 1 for r in raw])
    return words, np.searchsorted(starts, offsets)


def _pairs(words: np.ndarray) -> np.ndarray:
    """The flag of each pair of neighbouring words."""
    return (_mix(words[:-1] * _U(0xD6E8FEB86659FD93) + words[1:]) >> _U(64 - _FLAGS)).astype(np.int64)


def _sequences(words: np.ndarray, m: int) -> np.ndarray:
    """A hash of each m neighbouring words."""
    out = words[: len(words) - m + 1]
    for j in range(1, m):
        out = _mix(out * _U(0xD6E8FEB86659FD93) + words[j : len(words) - m + 1 + j])
    return out


def edit_distance_within(item: np.ndarray, stretch: np.ndarray) -> int:
    """The least number of word edits between the item and any part of the stretch."""
    places = np.arange(len(stretch) + 1)
    row = np.zeros(len(stretch) + 1, dtype=np.int64)
    for k, w in enumerate(item):
        new = np.empty_like(row)
        new[0] = k + 1
        new[1:] = np.minimum(row[:-1] + (stretch != w), row[1:] + 1)
        row = np.minimum.accumulate(new - places) + places
    return int(row.min())


def walk(rows: np.ndarray, sizes: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    """The embeddings of word sequences (rows padded with at least one zero) by one walk: two places a word."""
    each = np.arange(len(rows))
    steps = int(2 * sizes.max())
    out = np.empty((len(rows), steps), dtype=_U)
    at = np.zeros(len(rows), dtype=np.int64)
    for j in range(steps):
        word = rows[each, at]
        out[:, j] = word
        at = np.minimum(at + (_mix(word * seeds[j]) >> _U(63)).astype(np.int64), sizes)
    return out


@lru_cache(maxsize=16)
def walks_needed(size: int, recall: float, pairs: int = 96) -> int:
    """Walks after which simulated pairs at the edit limit meet with this recall: evenly spread replacements, and deletions."""
    edits = int(EDIT_SHARE * size)
    if edits == 0:
        return 1
    rng = np.random.default_rng([size, 6])
    a = rng.integers(1, 1 << 63, size=(2 * pairs, size + edits + 1)).astype(_U)
    b = a.copy()
    b[:pairs, np.arange(edits) * size // edits + size // edits // 2] ^= _U(1)
    for i in range(pairs, 2 * pairs):
        kept = np.setdiff1d(np.arange(size + edits), rng.choice(size, size=edits, replace=False))
        b[i, : len(kept)] = a[i, kept]
    a[:, size:] = b[:, size:] = 0
    sizes = np.full(2 * pairs, size)
    met = np.zeros(2 * pairs, dtype=bool)
    for w in range(MOST_WALKS):
        seeds = rng.integers(1, 1 << 63, size=2 * size + 1).astype(_U) | _U(1)
        same = walk(a, sizes, seeds) == walk(b, sizes, seeds)
        for places in rng.integers(0, 2 * size, size=(SETS, SAMPLED)):
            met |= same[:, places].all(axis=1)
        if met[:pairs].mean() >= recall and met[pairs:].mean() >= recall:
            return w + 1
    return MOST_WALKS


class Matcher:
    """The items of a block, ready to be met by texts."""

    def __init__(self, items: list[tuple[int, str]], recall: float = RECALL, complete: bool = True):
        self.complete = complete
        words, at = word_hashes([t for _, t in items])
        self.ids = [i for i, _ in items]
        self.words = [words[at[k] : at[k + 1]] for k in range(len(items))]
        sizes = np.diff(at)
        #: items without edits, by their size and words
        self.short: dict[int, dict[bytes, list[int]]] = {}
        for k in np.flatnonzero((sizes > 0) & (sizes < MIN_WORDS)).tolist():
            self.short.setdefault(int(sizes[k]), {}).setdefault(self.words[k].tobytes(), []).append(k)
        #: their hashes in order, by size
        self.short_keys = {m: np.sort(_sequences(np.concatenate([np.frombuffer(w, dtype=_U) for w in own]), m)[::m]) for m, own in self.short.items()}
        long = [int(k) for k in np.flatnonzero(sizes >= MIN_WORDS)]
        self.flags = np.zeros(1 << _FLAGS, dtype=np.uint8)
        for k in long:
            self.flags[_pairs(self.words[k])] = 1
        self.sizes = np.unique(sizes[long]) if long else np.zeros(0, dtype=np.int64)
        #: the least number of distinct pairs that an item of a size has
        self.distinct: dict[int, int] = {}
        #: the distinct pairs of each item
        self.own = {k: np.unique(_pairs(self.words[k])) for k in long}
        for k in long:
            m = int(sizes[k])
            self.distinct[m] = min(self.distinct.get(m, m), len(self.own[k]))
        self._index_rarest(long)
        self.mark = np.zeros(1 << _FLAGS, dtype=bool)
        #: (window, pairs it needs, sizes) of the first filter, for sizes within a sixteenth of each other
        self.classes: list[tuple[int, int, list[int]]] = []
        left = self.sizes.tolist()
        while left:
            window = left[0]
            own = [m for m in left if m <= window * 17 // 16]
            # A shorter window misses pairs of the item besides the two that each edit spoils; two may hide behind a repeat.
            need = min(self.distinct[m] - (m - window) - 2 * int(EDIT_SHARE * m) for m in own) - 2
            self.classes.append((window, max(1, need), own))
            left = left[len(own) :]
        self.most = int(self.sizes.max()) if long else 0
        rng = np.random.default_rng(20)
        self.walks = walks_needed(self.most, recall) if long else 0
        self.seeds = rng.integers(1, 1 << 63, size=(self.walks, 2 * self.most + 1)).astype(_U) | _U(1)
        self.draws = rng.random(size=(self.walks, SETS, SAMPLED))
        if long:
            rows = np.zeros((len(long), self.most), dtype=_U)
            for i, k in enumerate(long):
                rows[i, : sizes[k]] = self.words[k]
            columns = list(self._signatures(rows, sizes[long]))
            keys = np.concatenate(columns)
            order = np.argsort(keys, kind="stable")
            #: All signatures in order, and the item of each.
            self.keys, self.key_items = keys[order], np.tile(np.array(long), len(columns))[order]

    def _index_rarest(self, long: list[int]) -> None:
        """Of each item the rarest pairs, one more than its edits can spoil (all of an item with fewer), in order, and their items."""
        every = np.concatenate([np.zeros(0, dtype=np.int64), *self.own.values()])
        kinds, items_with = np.unique(every, return_counts=True)
        rare = []
        for k in long:
            own = self.own[k]
            spoiled = 2 * int(EDIT_SHARE * len(self.words[k]))
            rare.append(own[np.argsort(items_with[np.searchsorted(kinds, own)], kind="stable")[: spoiled + 1]])
        flat = np.concatenate([np.zeros(0, dtype=np.int64), *rare])
        order = np.argsort(flat, kind="stable")
        self.rare, self.rare_items = flat[order], np.repeat(np.array(long, dtype=np.int64), [len(r) for r in rare])[order]

    def _asked(self, kinds: np.ndarray) -> list[int]:
        """The items that have one of these pairs among their rarest."""
        left, right = np.searchsorted(self.rare, kinds, "left"), np.searchsorted(self.rare, kinds, "right")
        n = right - left
        at = np.repeat(left - (np.cumsum(n) - n), n) + np.arange(n.sum())
        return np.unique(self.rare_items[at]).tolist()

    def _signatures(self, rows: np.ndarray, sizes: np.ndarray):
        """For each walk and set, one signature of each row."""
        each = np.arange(len(rows))
        padded = np.hstack([rows, np.zeros((len(rows), 1), dtype=_U)])
        for w in range(self.walks):
            out = walk(padded, sizes, self.seeds[w])
            for k in range(SETS):
                s = sizes.astype(_U) * _U(_ODD) + _U(w * SETS + k)
                for d in self.draws[w, k]:
                    s = _mix(s + out[each, (d * 2 * sizes).astype(np.int64)])
                yield s

    def match(self, texts: list[str | None]) -> list[tuple[int, int, int]]:
        """(text's place, item's place, word edits) of all contaminations, sorted."""
        found: dict[tuple[int, int], int] = {}
        group, weight = [], 0
        for k, t in enumerate(texts):
            group.append(k)
            weight += len(t or "")
            if weight >= CHUNK or k == len(texts) - 1:
                self._match_group(group, [texts[g] or "" for g in group], found)
                group, weight = [], 0
        return sorted((t, i, d) for (t, i), d in found.items())

    def _match_group(self, places: list[int], texts: list[str], found: dict) -> None:
        words, at = word_hashes(texts)
        for m, own in self.short.items():
            if len(words) >= m:
                begins = np.flatnonzero(np.isin(_sequences(words, m), self.short_keys[m]))
                of = np.searchsorted(at, begins, side="right") - 1
                for b, k in zip(begins[begins + m <= at[of + 1]].tolist(), of[begins + m <= at[of + 1]].tolist()):
                    for i in own.get(words[b : b + m].tobytes(), ()):
                        found[places[k], i] = 0
        if len(words) < 2 or not self.classes:
            return
        pairs = _pairs(words)
        flags = self.flags[pairs]
        ends = at[1:-1]
        flags[ends[(ends > 0) & (ends <= len(pairs))] - 1] = 0  # no pair across texts
        once = flags.copy()
        once[1:] &= pairs[1:] != pairs[:-1]
        once[2:] &= pairs[2:] != pairs[:-2]
        # The pairs of one text do not hide those of the next.
        second = at[:-1][at[:-1] + 1 < len(pairs)] + 1
        once[second] = flags[second] & (pairs[second] != pairs[second - 1])
        start = at[:-1][at[:-1] < len(pairs)]
        once[start] = flags[start]
        sums = np.zeros(len(pairs) + 1 + self.most, dtype=np.int32)
        np.cumsum(once, out=sums[1 : len(pairs) + 1])
        sums[len(pairs) + 1 :] = sums[len(pairs)]  # windows at the end, and of texts shorter than them, are cut
        possible: dict[int, list[int]] = {}
        for window, need, own_sizes in self.classes:
            hit = np.flatnonzero(sums[window - 1 : window - 1 + len(pairs)] - sums[: len(pairs)] >= need)
            for k in np.unique(np.searchsorted(at, hit, side="right") - 1).tolist():
                possible.setdefault(k, []).extend(own_sizes)
        asked: list[tuple[int, int, np.ndarray]] = []
        windows: set[tuple[int, int, int]] = set()
        for k in sorted(possible):
            lo, hi, wanted = int(at[k]), int(at[k + 1]), set(possible[k])
            known = lo + np.flatnonzero(flags[lo : hi - 1])
            kinds = pairs[known]
            for i in self._asked(np.unique(kinds)):
                m = len(self.words[i])
                if m not in wanted or hi - lo < m - int(EDIT_SHARE * m):
                    continue
                self.mark[self.own[i]] = True
                mine = known[self.mark[kinds]]
                self.mark[self.own[i]] = False
                starts = self._windows(pairs, mine, lo, hi, i)
                if len(starts):
                    asked.append((k, i, starts))
                    windows.update((k, m, b) for b in starts.tolist())
        rows = sorted(windows)
        for part in range(0, len(rows), 4096):
            self._sample(words, at, places, rows[part : part + 4096], found)
        for k, i, starts in asked if self.complete else ():
            if found.get((places[k], i)) != 0:
                self._verify(words, at, places, k, i, starts.tolist(), found)

    def _windows(self, pairs: np.ndarray, known: np.ndarray, lo: int, hi: int, item: int) -> np.ndarray:
        """Where item-sized windows of a text begin that hold as many of the item's distinct pairs as its edits must leave."""
        m = len(self.words[item])
        need = max(1, len(self.own[item]) - 2 * int(EDIT_SHARE * m))
        if len(known) < need:
            return known[:0]
        # The place of the same pair before each known pair.
        kind = pairs[known]
        order = np.argsort(kind, kind="stable")
        before = np.full(len(known), lo - 1)
        same = kind[order][1:] == kind[order][:-1]
        before[order[1:][same]] = known[order[:-1][same]]
        # Pair i is new in the windows that begin after its earlier copy and still hold it whole.
        opens = np.maximum(before + 1, known - m + 2)
        count = np.zeros(hi - lo + 2, dtype=np.int64)
        ahead = opens <= known
        np.add.at(count, np.maximum(opens[ahead], lo) - lo, 1)
        np.add.at(count, known[ahead] + 1 - lo, -1)
        count = np.cumsum(count)[: max(1, hi - lo - m + 1)]  # a text shorter than the window is one window
        return lo + np.flatnonzero(count >= need)

    def _sample(self, words, at, places, windows, found) -> None:
        """Verify the items that windows (text, size, begin) meet in a sample of their embeddings."""
        block = np.zeros((len(windows), self.most), dtype=_U)
        for i, (k, m, b) in enumerate(windows):
            row = words[b : min(b + m, int(at[k + 1]))]
            block[i, : len(row)] = row
        met: dict[tuple[int, int], set[int]] = {}
        for column in self._signatures(block, np.array([m for _, m, _ in windows])):
            left, right = np.searchsorted(self.keys, column, "left"), np.searchsorted(self.keys, column, "right")
            for w in np.flatnonzero(right > left).tolist():
                for i in self.key_items[left[w] : right[w]].tolist():
                    met.setdefault((windows[w][0], i), set()).add(windows[w][2])
        for (k, i), starts in met.items():
            self._verify(words, at, places, k, i, sorted(starts), found)

    def _verify(self, words, at, places, text: int, item: int, starts: list[int], found) -> None:
        """Note the item if a stretch around these windows of the text is within its edits."""
        size = len(self.words[item])
        edits = int(EDIT_SHARE * size)
        # The stretches that the item may lie in, joined where they overlap.
        parts: list[list[int]] = []
        for b in starts:
            lo, hi = max(int(at[text]), b - edits), min(int(at[text + 1]), b + size + edits)
            if parts and lo <= parts[-1][1]:
                parts[-1][1] = max(parts[-1][1], hi)
            else:
                parts.append([lo, hi])
        d = min(edit_distance_within(self.words[item], words[lo:hi]) for lo, hi in parts)
        if d <= edits:
            key = (places[text], item)
            found[key] = min(d, found.get(key, d))


_MATCHERS: dict[str, Matcher] = {}


def matcher(key: str, items: Broadcast) -> Matcher:
    """The matcher of the items with this key, kept by the worker."""
    if key not in _MATCHERS:
        _MATCHERS.clear()
        _MATCHERS[key] = Matcher(items.value)
    return _MATCHERS[key]


def item_blocks(benchmark: DataFrame, block: int = BLOCK):
    """(key, broadcast list of (item_id, text)) of blocks of about ``block`` items or ``BLOCK_BYTES`` at most."""
    rows = benchmark.select("item_id", "text").where("text is not null")
    n, size = rows.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    parts = max(-(-n // block), -(-size // BLOCK_BYTES))
    for k in range(parts):
        part = rows if parts == 1 else rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == k)
        items = sorted(((r.item_id, r.text) for r in part.collect()), key=lambda r: (r[0] is None, r[0], r[1]))  # a block of bounded size
        yield hashlib.sha256(repr(items).encode("utf-8", "surrogatepass")).hexdigest(), benchmark.sparkSession.sparkContext.broadcast(items)


def contaminations(docs: DataFrame, benchmark: DataFrame, block: int = BLOCK) -> DataFrame:
    """doc_id, item_id, item_words, edits, similarity: one row for each row of ``docs`` and item that contaminates it."""
    schema = "doc_id bigint, item_id bigint, item_words bigint, edits bigint"
    out = docs.sparkSession.createDataFrame([], schema)
    for n, (key, items) in enumerate(item_blocks(benchmark, block)):

        def work(batch: pa.RecordBatch, key=key, items=items) -> pa.RecordBatch | None:
            own = matcher(key, items)
            hits = own.match(batch.column(1).to_pylist())
            if not hits:
                return None
            return pa.RecordBatch.from_arrays(
                [
                    batch.column(0).take(pa.array([t for t, _, _ in hits], type=pa.int64())),
                    pa.array([own.ids[i] for _, i, _ in hits], type=pa.int64()),
                    pa.array([len(own.words[i]) for _, i, _ in hits], type=pa.int64()),
                    pa.array([d for _, _, d in hits], type=pa.int64()),
                ],
                ["doc_id", "item_id", "item_words", "edits"],
            )

        found = map_texts(docs, ["doc_id", "text"], work, schema)
        out = out.unionByName(found) if n else found
    return out.withColumn("similarity", F.round(1 - F.col("edits") / F.col("item_words"), 6))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, block: int = BLOCK) -> DataFrame:
    """The rows of ``docs`` that no item contaminates, with all their columns."""
    names = docs.columns
    out = docs
    for key, items in item_blocks(benchmark, block):

        def work(batch: pa.RecordBatch, key=key, items=items) -> pa.RecordBatch:
            texts = batch.column(names.index("text")).to_pylist()
            bad = {t for t, _, _ in matcher(key, items).match(texts)}
            return batch.filter(pa.array([k not in bad for k in range(batch.num_rows)]))

        out = map_texts(out, [f"`{n}`" for n in names], work, out.schema)
    return out
