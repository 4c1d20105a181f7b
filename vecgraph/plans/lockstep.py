"""The gated search as joins: all queries move through one global graph in lock-step.

Each step is one plan: pivots join edges, the gate filters on columns of the edges
alone, passers join vectors, and a ranking window for each query decides what
enters the working set, the rings and the harvest. Only the rows of queries in
flight are shuffled; edges and vectors can stay bucketed by their keys. Vectors
are read for passers only. State is checkpointed at every step, which cuts the
lineage and lets a lost executor be replaced; the driver reads one count.

The rules are those of the array kernel, and so are the answers.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..operators.index import Index
from ..operators.projection import orthogonal, references, target_table
from ..sources.session import checkpoint

#: Sequence numbers of one step; a step moves fewer entries of a query than half of them.
STEP = 1 << 32
_STATE = ["qid", "node", "dist", "place", "expanded", "seq", "visits"]


def tables(index: Index) -> tuple[DataFrame, DataFrame]:
    """(edges with codes, vectors) of a one-shard index, by node place; vectors as doubles, rotated."""
    p = index.params
    rows = index.rows
    each = F.posexplode(F.arrays_zip("adj", "edge_len", "cos_own", "proj_src")).alias("at", "e")
    flat = rows.select(F.col("place").alias("src"), "codes", each)
    piece = F.expr(f"substring(codes, CAST(at * {p.blocks} + 1 AS INT), {p.blocks})")
    as_ints = F.transform(F.sequence(F.lit(0), F.lit(p.blocks - 1)), lambda l: F.conv(F.substr(F.hex("piece"), l * 2 + 1, F.lit(2)), 16, 10).cast("int"))
    edges = flat.select("src", F.col("e.adj").alias("dst"), F.col("e.edge_len").alias("a"), F.col("e.cos_own").alias("own"), F.col("e.proj_src").alias("shift"), piece.alias("piece"))
    edges = edges.select("src", "dst", "a", "own", "shift", as_ints.alias("codes"))
    kind = "<f2" if p.half else "<f4"

    @F.pandas_udf("array<double>")
    def floats(v):
        return v.map(lambda b: np.frombuffer(b, dtype=kind).astype(np.float64))

    return edges, rows.select(F.col("place").alias("dst"), floats("vector").alias("x"))


def _targets(index: Index, queries: DataFrame) -> DataFrame:
    """(qid, q, table): prepared query vectors and their products with all directions; all queries must fit the size that is sent at once."""
    from ..operators.index import SENT_FLOATS
    from ..operators.projection import prepare

    p = index.params
    if queries.count() * p.padded > SENT_FLOATS:
        raise ValueError("more queries than one lock-step run takes: search in blocks")
    rows = queries.select("qid", "qvec").collect()
    q = prepare(np.array([r.qvec for r in rows], dtype=np.float32).reshape(-1, p.dim), p, orthogonal(p.padded, p.seed))
    table = target_table(q, references(p.padded, p.blocks, p.refs_per_block, p.seed))
    data = [(r.qid, [float(v) for v in q[i]], [[float(v) for v in b] for b in table[i]]) for i, r in enumerate(rows)]
    return queries.sparkSession.createDataFrame(data, "qid bigint, q array<double>, table array<array<double>>")


def _l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda u, v: (u - v) * (u - v)), F.lit(0.0), lambda s, v: s + v))


def search(index: Index, queries: DataFrame, k: int, ef: int, gate: bool = True, most_steps: int | None = None) -> DataFrame:
    """(qid, rank, vec_id, dist, n_visited, n_exact): the k nearest found."""
    if index.shards != 1:
        raise ValueError("the lock-step search walks one global graph")
    p, ef = index.params, max(ef, k)
    w = min(p.work, ef) if p.rings else ef
    edges, vectors = (checkpoint(t) for t in tables(index))
    targets = checkpoint(_targets(index, queries))
    entries = index.rows.where("entry").select(F.col("place").alias("dst"))
    first = targets.select("qid", "q").crossJoin(F.broadcast(entries)).join(vectors, "dst").select("qid", F.col("dst").alias("node"), _l2(F.col("x"), F.col("q")).alias("dist"))  # a handful of entries
    by_q = Window.partitionBy("qid")
    near = by_q.orderBy("dist", "node")
    first = first.withColumn("n", F.row_number().over(near))
    state = first.select(
        "qid",
        "node",
        "dist",
        F.when(F.col("n") <= w, "work").otherwise("out").alias("place"),
        F.lit(False).alias("expanded"),
        F.col("n").cast("bigint").alias("seq"),
        F.lit(0).cast("bigint").alias("visits"),
    )
    state = checkpoint(state)
    for step in range(1, (most_steps or 8 * ef) + 1):
        state = _refill(state, w, ef, p.rings, step)
        open_ = state.where((F.col("place") == "work") & ~F.col("expanded") & (F.col("visits") < ef))
        pivots = open_.withColumn("n", F.row_number().over(near)).where("n = 1").select("qid", F.col("node").alias("src"), F.col("dist").alias("b"))
        pivots = checkpoint(pivots)
        if pivots.isEmpty():
            break
        state = checkpoint(_expand(state, pivots, edges, vectors, targets, w, gate, p.rings, step))
    done = state.where(F.col("place") != "gone")
    ranked = done.withColumn("rank", F.row_number().over(near)).withColumn("n_visited", F.col("visits"))
    measured = state.groupBy("qid").agg(F.count("*").alias("n_exact"))
    names = index.rows.select(F.col("place").alias("node"), "vec_id")
    return ranked.where(F.col("rank") <= k).join(names, "node").join(measured, "qid").select("qid", "rank", "vec_id", "dist", "n_visited", "n_exact")


def _refill(state: DataFrame, w: int, ef: int, rings: bool, step: int) -> DataFrame:
    """Round ends: where work is all expanded, it goes to harvest and the rings refill it."""
    by_q = Window.partitionBy("qid")
    idle = F.max(((F.col("place") == "work") & ~F.col("expanded")).cast("int")).over(by_q) == 0
    if not rings:
        return state
    marked = state.withColumn("idle", idle & (F.col("visits") < ef))
    ringed = F.col("idle") & F.col("place").isin("fp", "out")
    n = F.row_number().over(Window.partitionBy("qid", ringed).orderBy("dist", "node"))
    marked = marked.withColumn("n", F.when(ringed, n))
    place = F.when(F.col("idle") & (F.col("place") == "work"), "harvest").when(F.col("n") <= w, "work").when(F.col("n") > w, "out").otherwise(F.col("place"))
    seq = F.when(F.col("n").isNotNull(), F.col("n") + step * STEP).otherwise(F.col("seq"))
    return marked.select("qid", "node", "dist", place.alias("place"), "expanded", seq.alias("seq"), "visits")


def _expand(state: DataFrame, pivots: DataFrame, edges: DataFrame, vectors: DataFrame, targets: DataFrame, w: int, gate: bool, rings: bool, step: int) -> DataFrame:
    rim = state.where("place = 'work'").groupBy("qid").agg(F.when(F.count("*") >= w, F.max("dist")).alias("rim"))
    near = pivots.join(edges, "src").join(state.select("qid", F.col("node").alias("dst")), ["qid", "dst"], "left_anti").join(rim, "qid")
    asked = near.join(targets, "qid")
    if gate:
        dots = F.aggregate(F.transform("codes", lambda c, l: F.get(F.get("table", l), c)), F.lit(0.0), lambda s, v: s + v) - F.col("shift")
        estimate = dots / F.col("b") / F.col("own")
        tau = (F.col("a") * F.col("a") + F.col("b") * F.col("b") - F.col("rim") * F.col("rim")) / (2 * F.col("a") * F.col("b"))
        asked = asked.where(F.col("rim").isNull() | (F.col("a") == 0) | (F.col("b") == 0) | (estimate >= tau))
    new = asked.select("qid", "dst", "rim", "q").join(vectors, "dst")
    new = new.select("qid", F.col("dst").alias("node"), _l2(F.col("x"), F.col("q")).alias("dist"), "rim")
    seen = state.join(pivots.select("qid", F.col("src").alias("node"), F.lit(True).alias("now")), ["qid", "node"], "left").join(pivots.select("qid", F.lit(1).alias("moved")), "qid", "left")
    old = seen.select(
        "qid", "node", "dist", "place", (F.col("expanded") | F.coalesce("now", F.lit(False))).alias("expanded"), "seq", (F.col("visits") + F.coalesce("moved", F.lit(0))).alias("visits"), F.lit(None).cast("double").alias("rim")
    )
    visits = old.groupBy("qid").agg(F.max("visits").alias("visits"))
    fresh = new.join(visits, "qid").select("qid", "node", "dist", F.lit("new").alias("place"), F.lit(False).alias("expanded"), F.lit(0).cast("bigint").alias("seq"), "visits", "rim")
    both = old.unionByName(fresh)
    rival = F.col("place").isin("work", "new")
    n = F.row_number().over(Window.partitionBy("qid", rival).orderBy("dist", "node"))
    both = both.withColumn("n", F.when(rival, n))
    lost = F.col("n") > w
    place = (
        F.when(F.col("n") <= w, "work")
        .when(lost & F.col("expanded"), "harvest")
        .when(lost & (F.col("place") == "new") & (F.col("dist") >= F.col("rim")), "fp" if rings else "gone")
        .when(lost, "out" if rings else "gone")
        .otherwise(F.col("place"))
    )
    seq = F.when(lost, F.col("n") + step * STEP + STEP // 2).otherwise(F.col("seq"))
    both = both.select("qid", "node", "dist", place.alias("place"), "expanded", seq.alias("seq"), "visits")
    # Rings hold their newest w entries.
    age = F.row_number().over(Window.partitionBy("qid", "place").orderBy(F.desc("seq")))
    both = both.withColumn("age", age)
    return both.select("qid", "node", "dist", F.when(F.col("place").isin("fp", "out") & (F.col("age") > w), "gone").otherwise(F.col("place")).alias("place"), "expanded", "seq", "visits")
