"""SimHash near-duplicates by a segment-popcount grid.

A text's fingerprint has 64 bits: bit b is set when it is set in more than half
of the XXH64 values of the text's word shingles. Two fingerprints are linked if
at most three bits differ.

The embedding cuts a fingerprint in 32 segments of two bits and keeps each
segment's bit count (0, 1 or 2). The Manhattan distance of two such vectors is
never above the Hamming distance of their fingerprints, so a pair within three
bits is within Manhattan distance three, and then at least one half of the
vector (16 segments) is within distance one. The grid has a cell for each
half-vector: every point enters its own cell and, from one side only, the cells
one step up, so an equi-join on the cell finds all such pairs. Counts are kept
in unary (0 -> 00, 1 -> 01, 2 -> 11), which makes the Manhattan distance of two
vectors the bit count of their exclusive or. Survivors are verified on the
fingerprints.

Copies never meet in pairs: fingerprints are made distinct first (partial
aggregation takes the hot groups), and only distinct fingerprints are joined. A
cell that more than ``HOT_CELL`` distinct fingerprints own is not joined: all
fingerprints that enter it are linked through words at most one bit from one and
two bits from the other, each such word giving one star instead of all pairs.
That finds the same components, in work that grows with the fingerprints alone.

Cases: a null or blank text has fingerprint 0 and is linked like any other. A
null doc_id is never smaller than another id; a component of null ids only has
a null component_id. Repeated rows each keep a row. An empty table gives an
empty result.
"""

from __future__ import annotations

from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import checkpoint, map_texts

SHINGLE = 3
SEED = 42
MAX_BITS = 3
#: About where a cell's pairs outnumber the 1 + 64 + 2080 words around each of its fingerprints.
HOT_CELL = 4096
#: A node with more edges is a hub, whose edges are dealt by a salt.
HUB_EDGES = 1_000
SALTS = 32
#: The lower bit of each two-bit segment.
LOW = 0x5555555555555555
#: bits[v] holds the eight bits of byte v.
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.int64)


def fingerprint(text: str | None, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """The 64-bit fingerprint of one text, unsigned."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) < shingle:
        pieces = [b" ".join(words)]
    else:
        pieces = map(b" ".join, zip(*(islice(words, k, None) for k in range(shingle))))
    digest = xxhash.xxh64_intdigest
    values = np.array([digest(p, seed) for p in pieces], dtype=np.uint64)
    columns = values.view(np.uint8).reshape(-1, 8)
    if len(values) < 64:
        counts = _BITS[columns].sum(axis=0).ravel()
    else:
        counts = np.concatenate([np.bincount(columns[:, k], minlength=256) @ _BITS for k in range(8)])
    on = np.packbits((2 * counts > len(values)).astype(np.uint8), bitorder="little")
    return int(on.view(np.uint64)[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """(doc_id, fp): one row for each row of ``docs``; fp is the fingerprint as a signed long."""

    def work(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = np.array([fingerprint(t.as_py(), shingle, seed) for t in batch.column(1)], dtype=np.uint64)
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(found.view(np.int64))], ["doc_id", "fp"])

    return map_texts(docs, ["doc_id", "text"], work, "doc_id bigint, fp bigint")


def stars(points: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(a, b): links a < b among the distinct longs in ``points.fp`` that connect exactly what all links would.

    Two fingerprints are within three bits exactly if some word is within one bit
    of one and two of the other; whoever is within two bits of a word is linked to
    the least fingerprint within one bit of it.
    """
    flips = [0, *(1 << i for i in range(64))]
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    near, far = max_bits // 2, max_bits - max_bits // 2
    masks = {0: [0], 1: flips}
    array = lambda ms: F.array(*[F.lit(signed(m)).cast("bigint") for m in ms])
    own = points.select("fp", F.explode(array(masks[near])).alias("m")).select("fp", F.col("fp").bitwiseXOR(F.col("m")).alias("word"))
    hubs = own.groupBy("word").agg(F.min("fp").alias("hub"))
    # two flips of one bit each, drawn from one short list, instead of a list of all pairs
    twice = points.select("fp", F.explode(array(masks[near])).alias("m"))
    for _ in range(far - near):
        twice = twice.select("fp", "m", F.explode(array(flips)).alias("m2")).select("fp", F.col("m").bitwiseXOR(F.col("m2")).alias("m"))
    reach = twice.select("fp", F.col("fp").bitwiseXOR(F.col("m")).alias("word"))
    met = reach.join(hubs, "word").where("fp != hub")
    return met.select(F.least("fp", "hub").alias("a"), F.greatest("fp", "hub").alias("b")).distinct()


def links(points: DataFrame, max_bits: int = MAX_BITS, hot_cell: int = HOT_CELL) -> DataFrame:
    """(a, b): all pairs a < b of the distinct longs in ``points.fp`` within ``max_bits`` (at most 3); of hot cells, their stars."""
    if not 0 <= max_bits <= 3:
        raise ValueError("two halves and one step of the grid cover at most 3 bits")
    low = F.lit(LOW)
    halved = F.shiftrightunsigned("fp", 1)
    either = F.col("fp").bitwiseOR(halved).bitwiseAND(low)
    both = F.col("fp").bitwiseAND(halved).bitwiseAND(low)
    embedded = points.select("fp", either.bitwiseOR(F.shiftleft(both, 1)).alias("u"))
    halves = F.explode(
        F.array(
            F.struct(F.lit(0).alias("half"), F.col("u").bitwiseAND(F.lit(0xFFFFFFFF)).alias("key")),
            F.struct(F.lit(1).alias("half"), F.shiftrightunsigned("u", 32).alias("key")),
        )
    ).alias("cell")
    cells = embedded.select("fp", "u", halves).select("fp", "u", "cell.half", "cell.key")
    # One step up in segment i sets the next unary bit of that segment, if it has one left.
    steps = [
        F.when(F.col("key").bitwiseAND(F.lit(1 << (2 * i))) == 0, F.col("key").bitwiseOR(F.lit(1 << (2 * i)))).when(
            F.col("key").bitwiseAND(F.lit(2 << (2 * i))) == 0, F.col("key").bitwiseOR(F.lit(2 << (2 * i)))
        )
        for i in range(16)
    ]
    around = F.filter(F.array(F.col("key"), *steps), lambda k: k.isNotNull())
    raised = cells.select(F.col("fp").alias("b"), F.col("u").alias("ub"), "half", F.col("key").alias("own"), F.explode(around).alias("key"))
    hot = checkpoint(cells.groupBy("half", "key").count().where(F.col("count") > hot_cell).select("half", "key"))
    some_hot = not hot.isEmpty()
    own_side = cells.join(hot, ["half", "key"], "left_anti") if some_hot else cells
    met = own_side.select(F.col("fp").alias("a"), F.col("u").alias("ua"), "half", "key").join(
        raised,
        ["half", "key"],
    ).where(
        # within one cell each pair meets twice; across cells once
        ((F.col("own") != F.col("key")) | (F.col("a") < F.col("b")))
        & (F.bit_count(F.col("ua").bitwiseXOR(F.col("ub"))) <= max_bits)
        & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= max_bits)
    )
    pairs = met.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    if some_hot:
        entered = raised.join(hot, ["half", "key"], "left_semi").select(F.col("b").alias("fp")).distinct()
        pairs = pairs.union(stars(checkpoint(entered), max_bits))
    return pairs.distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root): connected components of ``edges(a, b)``; root is the smallest node.

    Alternates hooking each node to the least root next to it with halving the
    paths, on checkpointed tables; the number of rounds grows with the logarithm
    of a component's length.
    """
    both = checkpoint(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))))
    state = checkpoint(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("root")))
    # The edges of a hub are dealt by a salt, and its row is repeated for each salt.
    hubs = checkpoint(both.groupBy("b").count().where(F.col("count") > HUB_EDGES).select("b"))
    some_hubs = not hubs.isEmpty()
    salts = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt")
    salt = lambda c: F.pmod(F.xxhash64(c), F.lit(SALTS)).cast("int").alias("salt")
    if some_hubs:
        of_hubs = checkpoint(both.join(hubs, "b", "left_semi").select("a", "b", salt("a")))
        both = checkpoint(both.join(hubs, "b", "left_anti"))
    while True:
        roots = state.select(F.col("node").alias("b"), F.col("root").alias("rb"))
        met = both.join(roots, "b").select("a", "rb")
        if some_hubs:
            met = met.union(of_hubs.join(roots.join(hubs, "b", "left_semi").select("b", "rb", salts), ["b", "salt"]).select("a", "rb"))
        near = met.groupBy(F.col("a").alias("node")).agg(F.min("rb").alias("m"))
        seen = state.join(near, "node").select("node", "root", F.least("root", "m").alias("low"))
        # what any member has seen is offered to its root too
        offers = seen.groupBy(F.col("root").alias("node")).agg(F.min("low").alias("offer"))
        hooked = checkpoint(seen.join(offers, "node", "left").select("node", "root", F.least("low", F.coalesce("offer", "low")).alias("low")))
        # The few lows that have a lower one themselves; all members of a class share a low, so it is salted.
        above = hooked.select("low").distinct().join(hooked.select(F.col("node").alias("low"), F.col("low").alias("up")), "low").where("up < low").select("low", "up", salts)
        after = hooked.withColumn("salt", salt("node")).join(above, ["low", "salt"], "left")
        state = checkpoint(after.select("node", F.coalesce("up", "low").alias("root"), F.col("root").alias("was")))
        if state.where("root != was").isEmpty():
            return state.select("node", "root")
        state = state.select("node", "root")


def classes(prints: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(fp, component_id): the class of every distinct fingerprint in ``prints(doc_id, fp)``."""
    distinct = checkpoint(prints.groupBy("fp").agg(F.min("doc_id").alias("least_id")))
    edges = checkpoint(links(distinct, max_bits))
    roots = components(edges)
    of_fp = distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "least_id", F.coalesce("root", "fp").alias("root"), F.col("root").isNotNull().alias("linked"))
    linked = of_fp.where("linked")
    ids = linked.groupBy("root").agg(F.min("least_id").alias("component_id"))
    return of_fp.where("not linked").select("fp", F.col("least_id").alias("component_id")).union(linked.join(ids, "root").select("fp", "component_id"))


def near_duplicates(docs: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id: one row for each row of ``docs``."""
    prints = checkpoint(fingerprints(docs))
    out = prints.join(classes(prints, max_bits), "fp")
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """The rows of ``docs`` whose doc_id is their class's component_id, one row for each id.

    Of rows that repeat a kept id, the one with the least text stays; of a class
    whose ids are all null, one row stays.
    """
    prints = checkpoint(fingerprints(docs))
    chosen = classes(prints, max_bits).select(F.col("component_id").alias("__kept_id")).distinct()
    kept = docs.join(chosen, docs["doc_id"].eqNullSafe(chosen["__kept_id"]), "left_semi")
    repeated = prints.groupBy("doc_id").count().where("count > 1").select(F.col("doc_id").alias("__kept_id"))
    repeated = checkpoint(repeated)
    if repeated.isEmpty():
        return kept
    several = kept.join(repeated, docs["doc_id"].eqNullSafe(repeated["__kept_id"]), "left_semi")
    names = [c for c in docs.columns if c != "doc_id"]
    one = several.groupBy("doc_id").agg(F.min(F.struct(*[F.col(c) for c in sorted(names, key=lambda c: (c != "text", c))])).alias("__one"))
    one = one.select(*[F.col("doc_id") if c == "doc_id" else F.col(f"__one.`{c}`").alias(c) for c in docs.columns])
    return kept.join(repeated, docs["doc_id"].eqNullSafe(repeated["__kept_id"]), "left_anti").unionByName(one)
