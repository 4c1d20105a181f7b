"""Quality rules with verdicts on hosts, in DataFrame functions only.

Each document is measured (words, symbols, repeated lines, repeated three-word
windows) and tested against rules. Rule failures are then counted by host
(``source``), each host's failure rate of each rule is shrunk towards the mean
of all hosts by a beta prior fitted to the hosts by moments, and a host whose
shrunken rate of a rule exceeds that rule's limit is distrusted for it. A
document is kept when it passes the base rules and does not fail a rule for
which its host is distrusted.

Repeated windows: every window becomes one long with 40 bits of its XXH64 and 24
bits of its position; a primitive sort brings equal windows together. Neighbours
with equal hash bits are compared as texts, and a document in which two differ
(or with 2**24 words) is measured again by sorting the windows themselves, so
the counts are exact.

Cases: a null text has no words and fails the base rules; a blank one too. A
null host is a host of its own kind without a verdict: its documents are judged
alone. Repeated rows each count and each come back. An empty table gives an
empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .common import checkpoint

#: Fixed values of the base rules.
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: Rules that only count against a document of a distrusted host: the condition on the
#: measures, and the shrunken rate over which a host is distrusted.
HOST_RULES = {
    "symbols": ("n_symbols > 0.1 * n_words", 0.5),
    "short_words": ("word_chars < 3 * n_words", 0.5),
    "long_words": ("word_chars > 12 * n_words", 0.5),
    "dup_lines": ("n_dup_lines > 0.3 * n_lines", 0.5),
    "base": ("base_failed", 0.9),
}
#: Distrusted hosts are broadcast up to this many rows (a name and five flags each), joined by shuffle beyond.
BROADCAST_HOSTS = 50_000
SALTS = 32
_POSITION_BITS = 24
_SPACE = "[ \\t-\\r]+"
_MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def _covered(positions: Column) -> Column:
    """Words covered by three-word windows that start at the sorted ``positions``."""
    following = F.concat(F.slice(positions, 2, F.greatest(F.size(positions) - 1, F.lit(0))), F.array(F.lit(1 << 40).cast("bigint")))
    gaps = F.zip_with(positions, following, lambda a, b: F.least(b - a, F.lit(3).cast("bigint")))
    return F.when(F.size(positions) == 0, F.lit(0).cast("bigint")).otherwise(F.aggregate(gaps, F.lit(0).cast("bigint"), lambda s, g: s + g))


def measure(docs: DataFrame) -> DataFrame:
    """(row, q): each row of ``docs`` as a struct, and its measures (``_MEASURES``, ``n_lines``, ``base_failed``) as another."""
    df = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.coalesce(F.col("text"), F.lit("")).alias("t"))
    text = F.col("t")
    df = df.withColumn("__w", F.filter(F.split(text, _SPACE), lambda w: w != ""))
    n = F.size("__w")
    mask = F.lit((1 << _POSITION_BITS) - 1)
    starts = F.slice("__w", 1, F.greatest(n - 2, F.lit(0)))
    df = df.withColumn(
        "__keys",
        F.sort_array(
            F.transform(
                starts,
                lambda w, i: F.shiftleft(F.xxhash64(w, F.get("__w", i + 1), F.get("__w", i + 2)), _POSITION_BITS).bitwiseOR(i.cast("bigint")),
            )
        ),
    )
    # Neighbours in the sorted order with equal hash bits: (position, position of the one before).
    size = F.size("__keys")
    before = F.slice("__keys", 1, F.greatest(size - 1, F.lit(0)))
    after = F.slice("__keys", 2, F.greatest(size - 1, F.lit(0)))
    met = F.filter(
        F.zip_with(before, after, lambda a, b: F.struct(a.alias("a"), b.alias("b"))),
        lambda p: F.shiftright(p["a"], _POSITION_BITS) == F.shiftright(p["b"], _POSITION_BITS),
    )
    df = df.withColumn("__met", F.transform(met, lambda p: F.struct(p["a"].bitwiseAND(mask).alias("a"), p["b"].bitwiseAND(mask).alias("b"))))
    window = lambda i: F.slice("__w", i.cast("int") + 1, 3)
    clash = (n >= (1 << _POSITION_BITS)) | F.exists("__met", lambda p: window(p["a"]) != window(p["b"]))
    sorted_windows = F.array_sort(F.transform(starts, lambda w, i: F.struct(window(i).alias("w"), i.cast("bigint").alias("i"))))
    exact_met = lambda s: F.filter(
        F.zip_with(F.slice(s, 1, F.greatest(F.size(s) - 1, F.lit(0))), F.slice(s, 2, F.greatest(F.size(s) - 1, F.lit(0))), lambda a, b: F.struct(a["i"].alias("a"), b["i"].alias("b"), (a["w"] == b["w"]).alias("same"))),
        lambda p: p["same"],
    )
    slow = F.transform(exact_met(sorted_windows), lambda p: F.struct(p["a"].alias("a"), p["b"].alias("b")))
    df = df.withColumn("__met", F.when(clash, slow).otherwise(F.col("__met")))
    positions = F.sort_array(F.array_distinct(F.concat(F.transform("__met", lambda p: p["a"]), F.transform("__met", lambda p: p["b"]))))
    df = df.withColumn("__at", positions)
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.regexp_replace(x, _SPACE, "")) > 0)
    df = df.withColumn("__lines", lines)
    measured = F.struct(
        n.cast("bigint").alias("n_words"),
        F.length(F.array_join("__w", "")).cast("bigint").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("bigint").alias("n_symbols"),
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("bigint").alias("n_dup_lines"),
        _covered(F.col("__at")).alias("n_repeat_words"),
        F.size("__lines").cast("bigint").alias("n_lines"),
    )
    df = df.select("row", measured.alias("m"))
    failed = (F.col("m.n_words") < MIN_WORDS) | (100 * F.col("m.n_repeat_words") > MAX_REPEAT_PERCENT * F.col("m.n_words"))
    return df.select("row", F.col("m").withField("base_failed", failed).alias("q"))


def host_verdicts(measured: DataFrame, host: str = "source") -> DataFrame:
    """(host, n_docs, and for each rule its failures, shrunken rate and distrust) of each host that is not null.

    For each rule the prior's mean is the mean of the hosts' rates and its
    strength comes from their variance (method of moments); where all hosts
    agree, the strength is that of one host of mean size.
    """
    q = measured.select(F.col(f"row.`{host}`").alias("host"), "q.*")
    by_host = checkpoint(q.where("host is not null").groupBy("host").agg(F.count("*").alias("n_docs"), *[F.sum(F.expr(c).cast("bigint")).alias(f"{r}_failed") for r, (c, _) in HOST_RULES.items()]))
    rate = {r: F.col(f"{r}_failed") / F.col("n_docs") for r in HOST_RULES}
    prior = by_host.agg(F.avg("n_docs").alias("mean_docs"), *[f(rate[r]).alias(f"{r}_{n}") for r in HOST_RULES for n, f in (("mean", F.avg), ("var", F.var_samp))])
    out = by_host.crossJoin(F.broadcast(prior))  # the prior is one row
    for r, (_, limit) in HOST_RULES.items():
        m, v = F.col(f"{r}_mean"), F.col(f"{r}_var")
        strength = F.when((v > 0) & (m * (1 - m) > v), m * (1 - m) / v - 1).otherwise(F.col("mean_docs"))
        shrunk = (F.col(f"{r}_failed") + m * strength) / (F.col("n_docs") + strength)
        out = out.withColumn(f"{r}_rate", shrunk).withColumn(f"{r}_distrusted", shrunk > limit)
    return out.select("host", "n_docs", *[f"{r}_{x}" for r in HOST_RULES for x in ("failed", "rate", "distrusted")])


def judged(measured: DataFrame, verdicts: DataFrame, host: str = "source", row: str = "row") -> DataFrame:
    """(row, q, kept) of measured rows by the verdicts on their hosts."""
    distrusted = verdicts.select("host", F.struct(*[f"{r}_distrusted" for r in HOST_RULES]).alias("v")).where(" or ".join(f"v.{r}_distrusted" for r in HOST_RULES))
    distrusted = checkpoint(distrusted)
    own = F.col(f"{row}.`{host}`")
    if distrusted.count() <= BROADCAST_HOSTS:
        joined = measured.withColumn("host", own).join(F.broadcast(distrusted), "host", "left")
    else:  # the rows of a host are dealt by a salt, as one host may have most of them
        salt = F.pmod(F.xxhash64("q"), F.lit(SALTS)).cast("int")
        every = distrusted.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = measured.withColumn("host", own).withColumn("salt", salt).join(every, ["host", "salt"], "left")
    against = F.lit(False)
    for r, (condition, _) in HOST_RULES.items():
        against = against | (F.coalesce(F.col(f"v.{r}_distrusted"), F.lit(False)) & F.expr(_within(condition)))
    return joined.select("row", "q", (~F.col("q.base_failed") & ~against).alias("kept"))


def _within(condition: str) -> str:
    """The rule's condition on the fields of ``q``."""
    return " ".join(f"q.{t}" if t[0].isalpha() else t for t in condition.split())


def quality_report(docs: DataFrame, host: str = "source") -> DataFrame:
    """doc_id, the measures, base_failed and kept: one row for each row of ``docs``."""
    measured = measure(docs.select("doc_id", "text", host)).withColumn("row", F.col("row").dropFields("text"))
    measured = checkpoint(measured)
    out = judged(measured, host_verdicts(measured, host), host)
    return out.select("row.doc_id", *[f"q.{m}" for m in _MEASURES], "q.base_failed", "kept")


def keep_good(docs: DataFrame, host: str = "source") -> DataFrame:
    """The rows of ``docs`` that are kept, with the columns of ``docs``.

    Texts are measured twice, for the hosts' verdicts and for their own, rather
    than written in between: that takes processor time but no disk and little memory.
    """
    verdicts = host_verdicts(measure(docs.select("text", host)), host)
    # A row's number is not deterministic to the optimizer, so it does not measure anew in the filter what was measured.
    measured = measure(docs).withColumn("row", F.struct("row", F.monotonically_increasing_id().alias("number")))
    return judged(measured, verdicts, host, "row.row").where("kept AND row.number >= 0").select("row.row.*")


def quality_sql() -> str:
    """``quality_report`` of the documents table as SQL: windows are joined rows instead of sorted keys."""
    conditions = {r: c for r, (c, _) in HOST_RULES.items()}
    rates = ",\n".join(f"sum(CAST({c} AS INTEGER)) AS {r}_f" for r, c in conditions.items())
    prior = ",\n".join(f"avg({r}_f / n_docs) AS {r}_m, var_samp({r}_f / n_docs) AS {r}_v" for r in conditions)
    strength = lambda r: f"CASE WHEN {r}_v > 0 AND {r}_m * (1 - {r}_m) > {r}_v THEN {r}_m * (1 - {r}_m) / {r}_v - 1 ELSE mean_docs END"
    bad = ",\n".join(f"({r}_f + {r}_m * ({strength(r)})) / (n_docs + ({strength(r)})) > {limit} AS {r}_bad" for r, (_, limit) in HOST_RULES.items())
    against = " OR ".join(f"(coalesce({r}_bad, false) AND ({c}))" for r, c in conditions.items())
    return rf"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, source, coalesce(text, '') AS text FROM documents),
w AS (SELECT k, doc_id, source, text, list_filter(string_split_regex(text, '[ \t-\r]+'), lambda x: x <> '') AS words,
  list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^ \t-\r]')) AS lines FROM d),
p AS (SELECT k, unnest(range(1, len(words) - 1)) AS i, words FROM w WHERE len(words) >= 3),
g AS (SELECT k, i, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] AS win FROM p),
r AS (SELECT k, i FROM (SELECT k, i, count(*) OVER (PARTITION BY k, win) AS n FROM g) WHERE n > 1),
c AS (SELECT k, count(DISTINCT i + j) AS covered FROM r, (SELECT unnest([0, 1, 2]) AS j) GROUP BY k),
m AS (SELECT doc_id, source, CAST(len(words) AS BIGINT) AS n_words, CAST(length(array_to_string(words, '')) AS BIGINT) AS word_chars,
  CAST(length(text) - length(translate(text, '#*$%&|<>', '')) AS BIGINT) AS n_symbols,
  CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines, CAST(coalesce(covered, 0) AS BIGINT) AS n_repeat_words,
  CAST(len(lines) AS BIGINT) AS n_lines FROM w LEFT JOIN c USING (k)),
q AS (SELECT *, n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words AS base_failed FROM m),
h AS (SELECT source, CAST(count(*) AS DOUBLE) AS n_docs, {rates} FROM q WHERE source IS NOT NULL GROUP BY source),
b AS (SELECT avg(n_docs) AS mean_docs, {prior} FROM h),
v AS (SELECT source, {bad} FROM h, b)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT ({against}) AS kept
FROM q LEFT JOIN v USING (source)
"""
