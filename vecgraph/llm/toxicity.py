"""Toxicity by Levenshtein automata over a lexicon trie, with context windows.

The lexicon is learned from labelled rows: words, and stems that open many
different words, whose presence separates the two labels in texts that are no
copies of each other; a term that stands as often inside the words of clean
texts is a fragment and left out.
The lexicon's trie is intersected with the Levenshtein automaton of each term
(none, one or two edits by the term's length); the product is determinised step
by step as words are read, so a word costs one table lookup a character and most
die early. A word that clean training texts use is no misspelling.

Every hit is weighed by how its term separated the labels, and by its context:
within a window of words it counts as quoted (quotation marks around it or a
reporting word near) or as directed (a word of address near). A logistic model
over sums of plain, edited, quoted and directed hits gives the score. Labelled
rows hold few misspellings and quotations, so the model also learns from copies:
toxic texts whose hits are misspelled stay toxic, and clean texts into which a
report of a term is put stay clean.

Training reads a bounded sample of labelled rows (a parameter) outside the held-out
fold. Language, source and ids are no inputs.

Cases: a null or empty text has no hits and gets the score of the bias. Without
labels of both kinds every score is the share of toxic labels (0.5 without
any). Repeated rows each get a row; a null doc_id is in fold 0, held out; an
empty table gives an empty result.
"""

from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from .common import fold, map_texts, read_table

FOLDS, HELD_OUT = 5, 0
#: Labelled ids read for training.
TRAIN_ROWS = 4_000
REMEMBERED = 400_000
STATES = 100_000
WINDOW = 6
#: What a misspelled hit must weigh at least to count.
NOISE = 1.5
#: A labelled clean row counts as so many rows: calling it toxic is the worse error.
CLEAN_WEIGHT = 4.0
_WORD = re.compile(r"\w+")
_QUOTES = re.compile("[\"“”«»„‘‹›]")
#: Fixed context words.
REPORTING = frozenset("said says called calls quote quoted quoting word words term wrote reported slur insult".split())
ADDRESS = frozenset("you your youre yourself u du dich dein vous toi tu te usted eres".split())


def edits_allowed(length: int) -> int:
    return 0 if length < 4 else 1 if length < 9 else 2


def term_edits(term: str) -> int:
    """Edits allowed to a term; a stem, whose words go on, has one fewer."""
    return max(0, edits_allowed(len(term) - 1) - 1) if term.endswith("*") else edits_allowed(len(term))


class LexiconAutomaton:
    """The product of a lexicon trie with its terms' Levenshtein automata, determinised lazily.

    ``terms`` are words; one that ends in ``*`` is a stem and matches every word that opens with it.
    """

    def __init__(self, terms: list[str]):
        self.terms = terms
        self.children: list[dict[str, int]] = [{}]
        self.ends: list[int | None] = [None]
        self.budget = [0]
        self.stems: set[int] = set()
        for t, term in enumerate(terms):
            word = term.rstrip("*")
            allowed = term_edits(term)
            node = 0
            self.budget[0] = max(self.budget[0], allowed)
            for c in word:
                if c not in self.children[node]:
                    self.children[node][c] = len(self.children)
                    self.children.append({})
                    self.ends.append(None)
                    self.budget.append(0)
                node = self.children[node][c]
                self.budget[node] = max(self.budget[node], allowed)
            self.ends[node] = t
            if term.endswith("*"):
                self.stems.add(node)
        self._reset()

    def _reset(self) -> None:
        self.states: list[dict[int, int]] = []
        self.steps: list[dict[str, int]] = []
        self.numbers: dict[frozenset, int] = {}
        self.found: list[tuple[int, int] | None] = []
        self.start = self._number(self._closed({0: 0}))

    def _closed(self, at: dict[int, int]) -> dict[int, int]:
        """Positions reached by leaving out letters of a term."""
        todo = list(at.items())
        while todo:
            node, e = todo.pop()
            if e < at.get(node, 9):
                continue
            for child in self.children[node].values():
                if e + 1 <= self.budget[child] and e + 1 < at.get(child, 9):
                    at[child] = e + 1
                    todo.append((child, e + 1))
        return at

    def _number(self, at: dict[int, int]) -> int:
        key = frozenset(at.items())
        if key not in self.numbers:
            self.numbers[key] = len(self.states)
            self.states.append(at)
            self.steps.append({})
            ends = [(e, self.ends[n]) for n, e in at.items() if self.ends[n] is not None and e <= self.budget[n]]
            best = min(((e, t) for e, t in ends if e <= term_edits(self.terms[t])), default=None)
            self.found.append((best[1], best[0]) if best else None)
        return self.numbers[key]

    def _step(self, state: int, c: str) -> int:
        at: dict[int, int] = {}

        def reach(node: int, e: int) -> None:
            if e <= self.budget[node] and e < at.get(node, 9):
                at[node] = e

        for node, e in self.states[state].items():
            if node in self.stems:
                reach(node, e)  # whatever follows a stem belongs to its word
            for letter, child in self.children[node].items():
                reach(child, e + (letter != c))
            reach(node, e + 1)
        new = self._number(self._closed(at)) if at else -1
        self.steps[state][c] = new
        return new

    def match(self, word: str) -> tuple[int, int] | None:
        """(term's place, edits) of the nearest term, or None."""
        if len(self.states) > STATES:
            self._reset()
        state, steps = self.start, self.steps
        for c in word:
            after = steps[state].get(c)
            state = self._step(state, c) if after is None else after
            if state < 0:
                return None
        return self.found[state]


def _family(words: list[str]) -> int:
    """A number that copies and most near copies of a text share: the least hash of its five-word shingles."""
    return min((zlib.crc32(" ".join(words[i : i + 5]).encode("utf-8", "surrogatepass")) for i in range(max(1, len(words) - 4))), default=0)


def learn_lexicon(texts: list[str], labels: list[int], least_docs: int = 6, precision: float = 0.8) -> list[str]:
    """Words and stems present mostly in toxic texts, and in some that are no copies of each other, each stem standing for its words."""
    seen, toxic, families = Counter(), Counter(), {}
    for text, y in zip(texts, labels):
        in_order = _WORD.findall(text.lower())
        words = set(in_order)
        keys = words | {w[:k] + "*" for w in words for k in range(4, min(9, len(w)))}
        seen.update(keys)
        if y:
            toxic.update(keys)
            families.setdefault(_family(in_order), set()).update(keys)
    n, t = len(labels), sum(labels)
    if not 0 < t < n:
        return []
    apart = Counter(k for keys in families.values() for k in keys)
    share = max(precision, 2 * t / n)
    good = {k: c for k, c in toxic.items() if apart[k] >= least_docs and len(k) >= 3 and (c + 0.5) / (seen[k] + 1) >= share}
    words = {k for k in good if not k.endswith("*")}
    chosen: list[str] = []
    for k in sorted(good, key=lambda k: (len(k), k)):
        if not k.endswith("*"):
            if not any(k.startswith(s[:-1]) for s in chosen if s.endswith("*")):
                chosen.append(k)
            continue
        inside = [good[w] for w in words if w.startswith(k[:-1])]
        # A stem is kept if it says more than its best word and its next longer stems do.
        if good[k] > 1.5 * max(inside, default=0) and not any(k.startswith(s[:-1]) for s in chosen if s.endswith("*")):
            chosen.append(k)
    stems = [s[:-1] for s in chosen if s.endswith("*")]
    chosen = [k for k in chosen if k.endswith("*") or not any(k.startswith(s) for s in stems)]
    return _without_fragments(chosen, texts, labels, share)


def _without_fragments(terms: list[str], texts: list[str], labels: list[int], share: float) -> list[str]:
    """The terms that, wherever they stand inside words, mostly stand in toxic texts."""
    if not terms:
        return []
    inside = re.compile("(?=(" + "|".join(re.escape(t.rstrip("*")) for t in sorted(terms, key=len, reverse=True)) + "))")
    seen, toxic = Counter(), Counter()
    for text, y in zip(texts, labels):
        here = set(inside.findall(text.lower()))
        # of terms that begin at one place only the longest was found; its openings stand there too
        here |= {h[:k] for h in here for k in range(3, len(h))}
        seen.update(here)
        if y:
            toxic.update(here)
    return [t for t in terms if (toxic[t.rstrip("*")] + 0.5) / (seen[t.rstrip("*")] + 1) >= share]


def misspelled(word: str, rng: random.Random) -> str:
    """The word with one letter changed, doubled, left out or swapped with the next, the first one kept."""
    if len(word) < 4:
        return word
    k = rng.randrange(1, len(word) - 1)
    return rng.choice((word[:k] + rng.choice("aeioust") + word[k + 1 :], word[:k] + word[k] + word[k:], word[:k] + word[k + 1 :], word[:k] + word[k + 1] + word[k] + word[k + 2 :]))


class Model:
    """Lexicon, weights of its terms, the logistic model over its hits, and words of clean texts near the lexicon."""

    def __init__(self, terms: list[str], weights: dict[tuple[int, int], float], coefficients: np.ndarray, ordinary: frozenset[str] = frozenset()):
        self.terms, self.weights, self.coefficients, self.ordinary = terms, weights, coefficients, ordinary

    def scorer(self) -> Scorer:
        return Scorer(self)


class Scorer:
    """A model with the tables that grow as words are read."""

    def __init__(self, model: Model):
        self.model = model
        self.automaton = LexiconAutomaton(model.terms)
        self.known: dict[str, tuple[int, int] | None] = {}

    def hits(self, text: str) -> list[tuple[int, int, int, int, int]]:
        """(term, edits, quoted, directed, word's place) of every hit in the text."""
        lowered = text.lower()
        words = _WORD.findall(lowered)
        if len(self.known) > REMEMBERED:
            self.known.clear()
        known, match = self.known, self.automaton.match
        here = {}
        for w in set(words):
            if w in known:
                m = known[w]
            else:
                m = match(w)
                m = known[w] = None if m is not None and m[1] and w in self.model.ordinary else m
            if m is not None:
                here[w] = m
        if not here:
            return []
        out = []
        for i, m in enumerate(_WORD.finditer(lowered)):
            term = here.get(m.group())
            if term is None:
                continue
            around = words[max(0, i - WINDOW) : i] + words[i + 1 : i + 1 + WINDOW]
            before, after = lowered[max(0, m.start() - 40) : m.start()], lowered[m.end() : m.end() + 40]
            quoted = bool(_QUOTES.search(before) and _QUOTES.search(after)) or not REPORTING.isdisjoint(around)
            out.append((*term, int(quoted), int(not ADDRESS.isdisjoint(around)), i))
        return out

    def features(self, text: str) -> np.ndarray:
        sums = np.zeros(4)  # plain exact, edited, quoted, directed
        terms, top, n = set(), 0.0, 0
        for term, edits, quoted, directed, _ in self.hits(text):
            w = self.model.weights.get((term, edits), 0.0) - (NOISE if edits else 0.0)
            if w <= 0:
                continue
            sums[2 if quoted else 1 if edits else 0] += w
            if not quoted:
                n += not edits
                terms.add(term)
                top = max(top, 0.0 if edits else w)
                sums[3] += w * directed
        return np.array([1.0, *np.log1p(sums), top, math.log1p(len(terms)), n > 0, n > 1], dtype=np.float64)

    def score(self, text: str) -> float:
        z = float(self.features(text) @ self.model.coefficients)
        return 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, z))))


def copies(texts: list[str], labels: list[int], scorer: Scorer) -> tuple[list[str], list[int]]:
    """Copies to learn from: toxic texts with misspelled hits, and clean texts that report a term."""
    rng, terms = random.Random(11), scorer.model.terms
    more, marks = [], []
    clean = [t for t, y in zip(texts, labels) if not y]
    for text in [t for t, y in zip(texts, labels) if y]:
        words = {m.group() for m in _WORD.finditer(text.lower())}
        hits = {w for w in words if scorer.known.get(w)}
        if not hits:
            continue
        more.append(_WORD.sub(lambda m: misspelled(m.group(), rng) if m.group().lower() in hits else m.group(), text))
        marks.append(1)
        if clean:
            own = rng.choice(clean).split(" ")
            term = rng.choice(terms).rstrip("*")
            at = rng.randrange(len(own) + 1)
            own[at:at] = rng.choice(([f'said "{term}"'], ["the", "word", f'"{term}"', "is", "an", "insult"], ["wrote", f"“{term}”"]))
            more.append(" ".join(own))
            marks.append(0)
    return more, marks


def train(texts: list[str], labels: list[int], ridge: float = 1.0) -> Model:
    terms = learn_lexicon(texts, labels)
    n, t = len(labels), sum(labels)
    bias = math.log((t + 1) / (n - t + 1)) if n else 0.0
    if not terms:
        return Model([], {}, np.array([bias, 0, 0, 0, 0, 0, 0, 0, 0], dtype=np.float64))
    plain = LexiconAutomaton(terms)
    used = Counter(w for text, y in zip(texts, labels) if not y for w in set(_WORD.findall(text.lower())))
    ordinary = frozenset(w for w, c in used.items() if c > 1 and (m := plain.match(w)) is not None and m[1])
    model = Model(terms, {}, np.zeros(9), ordinary)
    scorer = model.scorer()
    seen, toxic = Counter(), Counter()
    for text, y in zip(texts, labels):
        keys = {(term, edits) for term, edits, *_ in scorer.hits(text)}
        seen.update(keys)
        if y:
            toxic.update(keys)
    more, marks = copies(texts, labels, scorer)
    # How often a misspelled term is met in toxic texts is counted in their copies.
    again = Counter(key for text, y in zip(more, marks) if y for key in {(term, edits) for term, edits, *_ in scorer.hits(text) if edits})
    for key in [(k, e) for k in range(len(terms)) for e in (0, 1, 2)]:
        bad, good = again[key] if key[1] else toxic[key], seen[key] - toxic[key]
        model.weights[key] = math.log((bad + 1) / (t + 2)) - math.log((good + 1) / (n - t + 2))
    x = np.stack([scorer.features(text) for text in [*texts, *more]])
    y, w = np.array([*labels, *marks], dtype=np.float64), np.zeros(9)
    each = np.array([*[1.0 if v else CLEAN_WEIGHT for v in labels], *[1.0] * len(marks)])
    w[0] = bias
    penalty = ridge * np.diag([1e-3] + [1.0] * (x.shape[1] - 1))

    def loss(w: np.ndarray) -> float:
        z = x @ w
        return float((each * (np.logaddexp(0, z) - y * z)).sum() + w @ penalty @ w / 2)

    now = loss(w)
    for _ in range(50):  # Newton's method; a step that raises the loss is halved
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (each * p * (1 - p))[:, None]).T @ x + penalty, x.T @ (each * (y - p)) - penalty @ w)
        while (after := loss(w + step)) > now and np.abs(step).max() > 1e-9:
            step /= 2
        w, gain, now = w + step, now - after, after
        if gain < 1e-9:
            break
    model.coefficients = w
    return model


def fit(docs: DataFrame, labels: DataFrame, cap: int = TRAIN_ROWS) -> Model:
    """Train on at most ``cap`` labelled ids outside the held-out fold, those with the least hashes."""
    rows = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull()).where(fold("doc_id", FOLDS) != HELD_OUT)
    ids = rows.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64(F.lit(7), "doc_id"), "doc_id").limit(cap)
    found = docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id").select("text", "toxic").limit(2 * cap).toLocalIterator()
    texts, marks = [], []
    for r in found:
        texts.append(r.text or "")
        marks.append(int(r.toxic > 0))
    return train(texts, marks)


def toxicity_report(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted: one row for each row of ``docs``."""

    def work(batch: pa.RecordBatch, own: list[Scorer] = []) -> pa.RecordBatch:  # noqa: B006  kept for the worker's batches
        if not own:
            own.append(model.scorer())
        scores = np.array([own[0].score(t or "") for t in batch.column(1).to_pylist()])
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores)], ["doc_id", "score"])

    scored = map_texts(docs, ["doc_id", "text"], work, "doc_id bigint, score double")
    return scored.select("doc_id", (fold("doc_id", FOLDS) == HELD_OUT).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def toxicity(spark: SparkSession, sf_dir: str, cap: int = TRAIN_ROWS) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return toxicity_report(docs, fit(docs, read_table(spark, sf_dir, "labels"), cap))
