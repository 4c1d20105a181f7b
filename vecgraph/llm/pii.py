"""Personal data by fixed patterns and a skip-chain conditional random field.

The base patterns give certain spans (email, ip, card, phone). Further segments
that look alike (runs of seven digits or more with separators, addresses
without a full domain, an address's local part standing alone) are uncertain.
The field has a node for each base span (its label observed) and each uncertain
segment. Neighbours in the text share chain potentials; segments with the same
key, however distant, share skip potentials (equal trailing digits, equal local
parts, or digits that differ in one place). Loopy sum-product passes messages
until labels settle; an uncertain segment whose label is most likely not
"other" becomes a span. Shape alone seldom makes it one: the patterns have
refused it already, and ``DOUBT`` says so; a link to a certain span outweighs it.

Skip links join consecutive members of a key's group, so their number is linear
in the segments of a document.

The weights are trained here: on a bounded sample of documents (a parameter) the
base spans are hidden and predicted from shape and context by a softmax, and the
two kinds of pair potentials come from label counts of linked pairs.

Cases: a null text is empty and has no spans. Offsets are code points, end
exclusive. With nothing to train on, no spans are added. Repeated rows each get
a row; a null doc_id stays null; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import map_texts, sample_rows

KINDS = ("email", "ip", "card", "phone")
LABELS = ("other", *KINDS)
#: Ids sampled for training.
TRAIN_DOCS = 4_000
ROUNDS = 60
#: What speaks against an uncertain segment: it has failed the patterns that made the labels.
DOUBT = 4.0
#: Bounds of the potential of two linked segments with one label.
AGREEMENT = (7.0, 9.0)

# Runs are taken whole (possessively) from their beginning, which matches the same
# spans as trying every place of a run, in linear time.
_LOCAL = "A-Za-z0-9._%+-"
_EMAIL = rf"[{_LOCAL}]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+"
_EMAIL_HERE = re.compile(_EMAIL)
_EMAIL_NEXT = re.compile(rf"(?<![{_LOCAL}]){_EMAIL}")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
_NUMBER = re.compile(r"[(]?[0-9](?:[\x20().-]{0,2}[0-9]){6,}")
_ADDRESS = re.compile(rf"(?<![{_LOCAL}])[{_LOCAL}]++@[A-Za-z0-9-]+")
_WORD = re.compile(r"\w+")
#: Fixed cue words by label.
CUES = {
    "email": ("email", "mail", "contact", "write"),
    "ip": ("ip", "host", "server", "address"),
    "card": ("card", "visa", "credit", "account"),
    "phone": ("phone", "tel", "call", "mobile", "fax"),
}


def _luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c)
        if k % 2:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _only_digits(s: str) -> str:
    return "".join(c for c in s if c in "0123456789")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind's place, end) of the base patterns, sorted."""
    out = []
    if "@" in text:
        at = 0
        while True:
            m = (_EMAIL_HERE.match(text, at) if at else None) or _EMAIL_NEXT.search(text, at)
            if m is None:
                break
            out.append((m.start(), 0, m.end()))
            at = m.end()
    if _DIGIT.search(text):
        for m in _IP.finditer(text):
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split(".")):
                out.append((m.start(), 1, m.end()))
        for m in _CARD.finditer(text):
            digits = _only_digits(m.group())
            if 14 <= len(digits) <= 19 and _luhn(digits):
                out.append((m.start(), 2, m.end()))
        if "+" in text:
            for m in _PHONE.finditer(text):
                if 10 <= len(_only_digits(m.group())) <= 15:
                    out.append((m.start(), 3, m.end()))
    return sorted(out)


def segments(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """(start, end, label) of the field's nodes in text order; label -1 where it is uncertain."""
    nodes = [(s, e, k + 1) for s, k, e in base]
    if not nodes and "@" not in text and not _DIGIT.search(text):
        return []
    ends = sorted((s, e) for s, _, e in base)

    def add(found):
        i = 0
        for s, e in found:
            while i < len(ends) and ends[i][1] <= s:
                i += 1
            if i == len(ends) or ends[i][0] >= e:
                nodes.append((s, e, -1))

    add([m.span() for m in _NUMBER.finditer(text)])
    if "@" in text:
        add([m.span() for m in _ADDRESS.finditer(text)])
        locals_ = {text[s:e].split("@")[0].casefold() for s, k, e in base if k == 0}
        locals_ = {x for x in locals_ if len(x) >= 6 and any(c.isalpha() for c in x) and any(c in "._0123456789" for c in x)}
        if locals_:
            add([m.span() for m in re.finditer(rf"(?<![{_LOCAL}])[{_LOCAL}]++(?!@)", text) if m.group().casefold().rstrip(".-") in locals_])
    nodes.sort()
    kept, last = [], -1
    for s, e, k in nodes:  # uncertain segments never overlap each other
        if k > 0 or s >= last:
            kept.append((s, e, k))
            last = max(last, e)
    return kept


def features(text: str, s: int, e: int) -> np.ndarray:
    """Shape and context of a segment."""
    own = text[s:e]
    n = len(_only_digits(own))
    before = _WORD.findall(text[max(0, s - 32) : s].lower())[-2:]
    f = [1.0, "@" in own, own.startswith("+") or text[max(0, s - 1) : s] == "+", own.count(".") == 3 and "@" not in own, "(" in own, " " in own or "-" in own]
    f += [n < 7, 7 <= n < 10, 10 <= n <= 13, 14 <= n <= 19, n > 19, n >= 14 and _luhn(_only_digits(own)), any(c.isalpha() for c in own)]
    f += [any(w in CUES[k] for w in before) for k in KINDS]
    return np.array(f, dtype=np.float64)


def skip_links(text: str, nodes: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """Pairs of distant segments that are equal or similar."""
    groups: dict[str, list[int]] = defaultdict(list)
    for i, (s, e, _) in enumerate(nodes):
        own = text[s:e]
        digits = _only_digits(own)
        if len(digits) >= 7 and "@" not in own:
            groups["tail " + digits[-7:]].append(i)
            # digits that differ in one of four pieces share the other three
            cut = [len(digits) * k // 4 for k in range(5)]
            for k in range(4):
                groups[f"near {len(digits)} {k} " + digits[: cut[k]] + "_" + digits[cut[k + 1] :]].append(i)
        elif any(c.isalpha() for c in own):
            groups["local " + own.split("@")[0].casefold().rstrip(".-")].append(i)
    return sorted({(a, b) for g in groups.values() for a, b in zip(g, g[1:])})


def chain_links(nodes: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    return [(i, i + 1) for i in range(len(nodes) - 1) if nodes[i + 1][0] - nodes[i][1] <= 64]


class Field:
    """Weights of the conditional random field."""

    def __init__(self, unary: np.ndarray, chain: np.ndarray, skip: np.ndarray):
        self.unary, self.chain, self.skip = unary, chain, skip

    def beliefs(self, text: str, nodes: list[tuple[int, int, int]]) -> np.ndarray:
        """Label probabilities of each node by loopy sum-product."""
        n, k = len(nodes), len(LABELS)
        local = np.stack([features(text, s, e) @ self.unary for s, e, _ in nodes])
        for i, (_, _, label) in enumerate(nodes):
            if label > 0:
                local[i] = -50.0
                local[i, label] = 0.0
            else:
                local[i, 0] += DOUBT
        links = [(a, b, self.chain) for a, b in chain_links(nodes)] + [(a, b, self.skip) for a, b in skip_links(text, nodes)]
        if links:
            # Both directions of each link: the message of edge j goes from src[j] to dst[j].
            src = np.array([x for a, b, _ in links for x in (a, b)])
            dst = np.array([x for a, b, _ in links for x in (b, a)])
            pots = np.stack([p for _, _, w in links for p in (w, w.T)])
            back = np.arange(len(src)) ^ 1
            messages = np.zeros((len(src), k))
            for _ in range(ROUNDS):
                total = local.copy()
                np.add.at(total, dst, messages)
                out = (total[src] - messages[back])[:, :, None] + pots
                peak = out.max(axis=1)
                new = peak + np.log(np.exp(out - peak[:, None, :]).sum(axis=1))
                new -= new.max(axis=1, keepdims=True)
                moved = np.abs(new - messages).max()
                messages = 0.5 * messages + 0.5 * new
                if moved < 1e-6:
                    break
            np.add.at(local, dst, messages)
        local -= local.max(axis=1, keepdims=True)
        p = np.exp(local)
        return p / p.sum(axis=1, keepdims=True)


def train(texts: list[str], steps: int = 300) -> Field | None:
    """The field's weights from texts labelled by the base patterns."""
    x, y, chain, skip = [], [], np.ones((5, 5)), np.ones((5, 5)) + 3 * np.eye(5)
    for text in texts:
        nodes = segments(text, base_spans(text))
        labels = [max(k, 0) for _, _, k in nodes]
        x += [features(text, s, e) for s, e, _ in nodes]
        y += labels
        for links, counts in ((chain_links(nodes), chain), (skip_links(text, nodes), skip)):
            for a, b in links:
                counts[labels[a], labels[b]] += 1
                counts[labels[b], labels[a]] += 1
    if not y or not any(y):
        return None
    x, y = np.stack(x), np.array(y)
    w, target = np.zeros((x.shape[1], len(LABELS))), np.eye(len(LABELS))[y]
    for _ in range(steps):
        p = np.exp(x @ w - (x @ w).max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        w += 0.5 * (x.T @ (target - p) / len(y) - 1e-3 * w)
    # Pair potentials: how much more often two labels are linked than chance has it. A
    # base label is hidden from nobody, so a skip link from "other" says nothing against;
    # where nearly all links join one label chance explains them, so agreement has a floor.
    pot = lambda c: np.log(c / c.sum() / np.outer(c.sum(0), c.sum(1)) * c.sum() ** 2)
    skip_pot = np.clip(pot(skip), *AGREEMENT) * np.eye(len(LABELS))
    skip_pot[0, 0] = 0.0
    return Field(w, np.clip(pot(chain), -2.0, 2.0), skip_pot)


def find(text: str, field: Field | None) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(base spans, all spans) of a text, each (start, kind's place, end), sorted."""
    base = base_spans(text)
    if field is None:
        return base, base
    nodes = segments(text, base)
    if not any(k < 0 for _, _, k in nodes):
        return base, base
    p = field.beliefs(text, nodes)
    added = [(s, int(q.argmax()) - 1, e) for (s, e, k), q in zip(nodes, p) if k < 0 and q.argmax() > 0]
    return base, sorted(base + added)


def fit(docs: DataFrame, cap: int = TRAIN_DOCS) -> Field | None:
    """Train on a sample of at most ``cap`` ids."""
    rows = sample_rows(docs, ["text"], cap).where(F.col("text").rlike("[0-9@]")).select("text").toLocalIterator()
    return train([r.text for r in rows])


def _show(spans) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def pii_report(docs: DataFrame, field: Field | None = None, cap: int = TRAIN_DOCS) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans: one row for each row of ``docs``."""
    field = field or fit(docs, cap)

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        counts, digests, shown = [], [], []
        for t in batch.column(1).to_pylist():
            base, spans = find(t or "", field)
            counts.append([sum(k == j for _, k, _ in base) for j in range(4)])
            digests.append(hashlib.sha256(_show(base).encode()).hexdigest())
            shown.append(_show(spans))
        by_kind = [pa.array([c[j] for c in counts], type=pa.int64()) for j in range(4)]
        return pa.RecordBatch.from_arrays([batch.column(0), *by_kind, pa.array(digests), pa.array(shown)], ["doc_id", *[f"n_{k}" for k in KINDS], "base_sha256", "spans"])

    return map_texts(docs, ["doc_id", "text"], work, "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string")


def mask(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text with each span (overlapping ones as one) replaced by its kind in brackets."""
    out, at = [], 0
    for s, k, e in spans:
        if s >= at:
            out += [text[at:s], f"[{KINDS[k].upper()}]"]
        at = max(at, e)
    return "".join(out) + text[at:]


def redact(docs: DataFrame, field: Field | None = None, cap: int = TRAIN_DOCS) -> DataFrame:
    """``docs`` with personal data masked in ``text``; ``n_chars``, if there and not null, follows. All rows and columns stay."""
    field = field or fit(docs, cap)
    names = docs.columns
    sized = "n_chars" in names
    schema = docs.schema

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        columns = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
        old = columns["text"].to_pylist()
        new = [None if t is None else mask(t, find(t, field)[1]) for t in old]
        columns["text"] = pa.array(new, type=pa.string())
        if sized:
            kind = columns["n_chars"].type
            columns["n_chars"] = pa.array([n if n is None or a == b else len(b) for n, a, b in zip(columns["n_chars"].to_pylist(), old, new)], type=kind)
        return pa.RecordBatch.from_arrays(list(columns.values()), list(columns))

    return map_texts(docs, [f"`{n}`" for n in names], work, schema)
