"""Secret scan through a trigram inverted index, in DataFrame functions only.

Each rule's regular expression is turned into a Boolean query over trigrams that
every match must contain (of the lower-cased text, so letter case never loses a
match). The index holds a posting (trigram, doc_id) for each trigram of any
query and each document that contains it; the postings of a document are
intersected by evaluating the queries on its set of trigrams. Only candidates are
verified with the expression itself. A rule without mandatory trigrams (the
hexadecimal one) scans every text.

Spans come from the gaps and matches that one expression cuts a text into: a
match starts after all gaps and matches before it. Offsets are code points, end
exclusive.

Cases: a null text is empty. A null doc_id has postings of its own; repeated ids
share candidates, which verification makes exact for each row. Very long texts
are read whole. An empty table gives an empty result.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from re import _constants as rc
from re import _parser as rp

from pyspark.sql import Column, DataFrame, functions as F

from .common import checkpoint


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    base: bool = False
    #: (group, least length): other matches are dropped
    least: tuple[int, int] = (0, 1)


#: The base rules as given, in their order, then the rules this method adds.
RULES = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", True, (2, 6)),
    Rule("access", r"AKIA[A-Z0-9]+", True, (0, 20)),
    Rule("hex", r"[0-9a-f]{24,}", True),
    Rule("pem", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("cloud", r"AIza[A-Za-z0-9_-]{35}"),
    Rule("pay", r"sk_live_[A-Za-z0-9]{16,}"),
)
#: Candidates are broadcast up to this many rows (an id and a long each), joined by shuffle beyond.
BROADCAST_CANDIDATES = 200_000
_MOST_STRINGS = 64


def trigram_query(pattern: str):
    """The Boolean query of a pattern: a trigram, ("and", parts), ("or", parts), or None if nothing is mandatory."""

    def both(op, parts):
        flat = []
        for p in parts:
            flat += p[1] if isinstance(p, tuple) and p[0] == op else [p]
        unique = list(dict.fromkeys(flat))
        return unique[0] if len(unique) == 1 else (op, tuple(unique))

    def of_strings(strings):
        """Some one of the strings occurs."""
        each = []
        for s in sorted(strings):
            if len(s) < 3:
                return None
            each.append(both("and", [s[i : i + 3] for i in range(len(s) - 2)]))
        return both("or", each)

    def conjunction(found):
        found = [q for q in found if q is not None]
        return both("and", found) if found else None

    def walk(items):
        """(strings, query): all strings the items match if few, else None; and what else is mandatory."""
        run, found = {""}, []

        def close(now):
            nonlocal run
            found.append(of_strings(run))
            run = now

        for op, arg in items:
            strings, query = None, None
            if op is rc.LITERAL:
                strings = {chr(arg).lower()}
            elif op is rc.IN and all(o is rc.LITERAL for o, _ in arg):
                strings = {chr(a).lower() for _, a in arg}
            elif op is rc.SUBPATTERN:
                strings, query = walk(arg[3])
            elif op is rc.BRANCH:
                sides = [walk(b) for b in arg[1]]
                if all(s is not None for s, _ in sides):
                    strings = set().union(*(s for s, _ in sides))
                else:
                    queries = [conjunction([q, of_strings(s) if s is not None else None]) for s, q in sides]
                    query = None if any(q is None for q in queries) else both("or", queries)
            elif op in (rc.MAX_REPEAT, rc.MIN_REPEAT, rc.POSSESSIVE_REPEAT):
                low, high, inner = arg
                strings, query = walk(inner)
                if low == 0 and min(map(len, run)) >= 3:
                    strings, query = None, None  # an optional part only multiplies the strings before it
                elif (low, high) == (0, 1) and strings is not None:
                    strings, query = strings | {""}, None
                elif low == 0:
                    strings, query = None, None
                elif (low, high) != (1, 1):
                    query, strings = conjunction([query, of_strings(strings) if strings is not None else None]), None
            if strings is not None and len(run) * len(strings) <= _MOST_STRINGS:
                found.append(query)
                run = {a + b for a in run for b in strings}
            else:
                close({""})
                found.append(query)
                if strings is not None and len(strings) <= _MOST_STRINGS:
                    run = set(strings)
        if not any(q is not None for q in found):
            # the whole is a set of strings if nothing closed the run on the way
            return (run, None) if not found or all(q is None for q in found) and run != {""} and _whole(items) else (None, of_strings(run))
        found.append(of_strings(run))
        return None, conjunction(found)

    strings, query = walk(rp.parse(pattern))
    return conjunction([query, of_strings(strings) if strings is not None else None])


def _whole(items) -> bool:
    """Whether every item has few strings, so that a run holds the whole."""
    for op, arg in items:
        if op is rc.LITERAL or op is rc.IN and all(o is rc.LITERAL for o, _ in arg):
            continue
        if op is rc.SUBPATTERN and _whole(arg[3]):
            continue
        if op is rc.BRANCH and all(_whole(b) for b in arg[1]):
            continue
        if op is rc.MAX_REPEAT and arg[:2] == (0, 1) and _whole(arg[2]):
            continue
        return False
    return True


def trigrams_of(query) -> set[str]:
    if query is None:
        return set()
    return {query} if isinstance(query, str) else set().union(*(trigrams_of(q) for q in query[1]))


def _holds(query, present: Column) -> Column:
    if isinstance(query, str):
        return F.array_contains(present, query)
    out = None
    for q in query[1]:
        c = _holds(q, present)
        out = c if out is None else (out & c if query[0] == "and" else out | c)
    return out


def postings(docs: DataFrame, rules=RULES) -> DataFrame:
    """(trigram, doc_id): the inverted index over the trigrams that the rules' queries use."""
    vocabulary = sorted(set().union(*(trigrams_of(trigram_query(r.pattern)) for r in rules)))
    lowered = docs.select("doc_id", F.lower("text").alias("lowered"))
    held = [F.when(F.contains("lowered", F.lit(t)), F.lit(t)) for t in vocabulary]
    return lowered.select("doc_id", F.explode(F.array_compact(F.array(*held))).alias("trigram")).select("trigram", "doc_id")


def candidates(index: DataFrame, rules=RULES) -> DataFrame:
    """(doc_id, wanted): for each document that some query selects, a bit for each such rule."""
    by_doc = index.groupBy("doc_id").agg(F.collect_set("trigram").alias("present"))
    bits = F.lit(0).cast("bigint")
    for k, r in enumerate(rules):
        if (query := trigram_query(r.pattern)) is not None:
            bits = bits + F.when(_holds(query, F.col("present")), F.lit(1 << k)).otherwise(F.lit(0))
    return by_doc.select("doc_id", bits.alias("wanted")).where("wanted > 0")


def _spans(rule: Rule, order: int, text: Column) -> Column:
    """array<struct<start, order, end, ok>>: all matches of the rule in the text."""
    group, least = rule.least
    matches = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    gaps = F.split(text, F.lit(rule.pattern), -1)
    lengths = F.zip_with(gaps, matches, lambda g, m: F.struct(F.length(g).alias("gap"), F.length(m).alias("own")))
    kind = "array<struct<start:bigint,order:int,end:bigint>>"
    walked = F.aggregate(
        lengths,
        F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast(kind).alias("spans")),
        lambda s, x: F.when(x["own"].isNull(), s).otherwise(
            F.struct(
                (s["at"] + x["gap"] + x["own"]).alias("at"),
                F.concat(
                    s["spans"],
                    F.array(F.struct((s["at"] + x["gap"]).alias("start"), F.lit(order).alias("order"), (s["at"] + x["gap"] + x["own"]).alias("end"))),
                ).alias("spans"),
            )
        ),
    )["spans"]
    if group == 0:
        return F.filter(walked, lambda s: s["end"] - s["start"] >= least)
    sizes = F.transform(F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(group)), lambda g: F.length(g))
    return F.filter(F.transform(walked, lambda s, i: F.when(F.get(sizes, i) >= least, s)), lambda s: s.isNotNull())


def find_secrets(docs: DataFrame, rules=RULES) -> DataFrame:
    """``doc_id, text`` rows of ``docs`` with ``secrets``: array<struct<start, order, end>>, sorted; order is the rule's place."""
    found = checkpoint(candidates(postings(docs, rules), rules)).select(F.col("doc_id").alias("__id"), "wanted")
    if found.count() <= BROADCAST_CANDIDATES:
        found = F.broadcast(found)
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.join(found, rows["doc_id"].eqNullSafe(found["__id"]), "left").drop("__id")
    nothing = F.array().cast("array<struct<start:bigint,order:int,end:bigint>>")
    parts = []
    for k, r in enumerate(rules):
        scan = _spans(r, k, F.col("text"))
        if trigram_query(r.pattern) is None:
            parts.append(F.when(F.col("text").rlike(r.pattern), scan).otherwise(nothing))
        else:
            parts.append(F.when(F.coalesce(F.col("wanted").bitwiseAND(F.lit(1 << k)), F.lit(0)) != 0, scan).otherwise(nothing))
    return rows.select("doc_id", "text", F.array_sort(F.concat(*parts)).alias("secrets"))


def secret_report(docs: DataFrame, rules=RULES) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256 and spans: one row for each row of ``docs``."""
    kinds = F.array(*[F.lit(r.kind) for r in rules])
    base = [k for k, r in enumerate(rules) if r.base]
    shown = lambda s: F.concat_ws(":", F.get(kinds, s["order"]), s["start"], s["end"])
    own = F.filter("secrets", lambda s: s["order"].isin(base))

    def of_kind(k):
        return F.filter("secrets", lambda s: s["order"] == k)

    found = find_secrets(docs, rules)
    return found.select(
        "doc_id",
        *[F.size(of_kind(k)).cast("bigint").alias(f"n_{rules[k].kind}") for k in base],
        F.sha2(F.array_join(F.transform(own, shown), ","), 256).alias("base_sha256"),
        F.array_join(F.transform("secrets", shown), ",").alias("spans"),
    )


def secrets_sql(rules=RULES) -> str:
    """The same result as SQL: every rule scans every text."""
    parts, names = [], []
    for k, r in enumerate(rules):
        p = r.pattern.replace("'", "''")
        group, least = r.least
        sizes = f"list_transform(regexp_extract_all(t, '{p}', {group}), lambda m: length(m))"
        parts.append(
            f"""list_filter(list_transform(range(1, len(regexp_extract_all(t, '{p}')) + 1), lambda i: {{
              's': CAST(coalesce(list_sum(list_transform(string_split_regex(t, '{p}')[1:i], lambda g: length(g))), 0)
                 + coalesce(list_sum(list_transform(regexp_extract_all(t, '{p}')[1:i-1], lambda g: length(g))), 0) AS BIGINT),
              'o': {k},
              'n': CAST(length(regexp_extract_all(t, '{p}')[i]) AS BIGINT),
              'ok': {sizes}[i] >= {least}}}), lambda x: x.ok)"""
        )
        names.append(f"'{r.kind}'")
    kinds = "[" + ", ".join(names) + "]"
    show = f"lambda x: {kinds}[x.o + 1] || ':' || x.s || ':' || (x.s + x.n)"
    n_base = sum(r.base for r in rules)
    counts = ", ".join(f"CAST(len(list_filter(f, lambda x: x.o = {k})) AS BIGINT) AS n_{r.kind}" for k, r in enumerate(rules) if r.base)
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
m AS (SELECT doc_id, list_sort(flatten([{', '.join(parts)}])) AS f FROM d)
SELECT doc_id, {counts},
  sha256(array_to_string(list_transform(list_filter(f, lambda x: x.o < {n_base}), {show}), ',')) AS base_sha256,
  array_to_string(list_transform(f, {show}), ',') AS spans
FROM m
"""


def reference_spans(text: str | None, rules=RULES) -> list[tuple[int, str, int]]:
    """Brute force for tests: (start, kind, end) of every rule over the whole text."""
    out = []
    for k, r in enumerate(rules):
        group, least = r.least
        out += [(m.start(), k, m.end()) for m in re.finditer(r.pattern, text or "", re.ASCII) if len(m.group(group)) >= least]
    return [(s, rules[k].kind, e) for s, k, e in sorted(out)]
