"""The methods: projections, gate, screen, and graphs with every variant.

What deterministic directions can express has its SQL; a search as wide as its
graph, without a gate, must give the exact answers and has theirs.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, functions as F

from ..functions import vectors as V

from ..operators import baselines as B
from ..operators import exact as E
from ..operators import gate as G
from ..operators import measures as M
from ..operators import projection as P
from ..operators import quantised as Z
from ..operators.index import build_index, insert_batch
from ..params import Params
from ..plans import experiments as X
from ..sources import corpora as C
from ..sources.session import checkpoint, materialise
from .base import Book
from .vectors import NATIVE_Q, dot, knn_graph, knn_sql, l2, native, rounded

BOOK = Book()
DIM, BLOCKS, REFS = 64, 8, 16

# --- SQL of the deterministic family ------------------------------------------------


def _family(blocks: int, refs: int) -> tuple[str, str]:
    """SQL of the directions and of the profiles with them."""
    return tuple(
        s.replace("range(0, 8)) AS b", f"range(0, {blocks})) AS b").replace("range(0, 16)", f"range(0, {refs})").replace("range(0, 8), lambda j", f"range(0, {DIM // blocks}), lambda j")
        .replace("0.125", "CAST(0.125 AS DOUBLE)").replace("block * 8 + 1 : block * 8 + 8", f"block * {DIM // blocks} + 1 : block * {DIM // blocks} + {DIM // blocks}")
        for s in (_REFS, _PROFILE)
    )


_REFS = """refs AS (SELECT CAST(b AS INTEGER) AS block, CAST(r AS INTEGER) AS ref, list_transform(range(0, 8), lambda j:
  (CASE WHEN r % 2 = 0 THEN 1.0 ELSE -1.0 END) * (CASE WHEN bit_count(CAST((r // 2) & j AS BIGINT)) % 2 = 0 THEN 1.0 ELSE -1.0 END) * 0.125) AS dir
  FROM (SELECT unnest(range(0, 8)) AS b), (SELECT unnest(range(0, 16)) AS r))"""
_GRAPH = knn_sql("SELECT vec_id, embedding FROM embeddings", "SELECT vec_id AS qid, embedding AS qvec FROM embeddings", 12, where="WHERE vec_id <> qid").replace("round(dist, 6)", "dist")
_TRIPLES = f"""e AS (SELECT qid AS src, vec_id AS dst, dist, rank FROM ({_GRAPH})),
  t AS (SELECT {{'q': a.src, 'x': b.dst}} AS t, p.embedding AS p, q.embedding AS q, x.embedding AS x, z.dist AS r FROM e a JOIN e b ON b.src = a.dst AND b.dst <> a.src
    JOIN e z ON z.src = a.src AND z.rank = 12 JOIN embeddings p ON p.vec_id = a.dst JOIN embeddings q ON q.vec_id = a.src JOIN embeddings x ON x.vec_id = b.dst WHERE a.rank = 5)"""
_PROFILE = f"""d AS (SELECT t, r, list_transform(list_zip(x, p), lambda z: CAST(z[1] AS DOUBLE) - z[2]) AS edge, list_transform(list_zip(q, p), lambda z: CAST(z[1] AS DOUBLE) - z[2]) AS way FROM t),
  s AS (SELECT t, block, ref, list_sum(list_transform(list_zip(edge[block * 8 + 1 : block * 8 + 8], dir), lambda z: z[1] * z[2])) AS own,
    list_sum(list_transform(list_zip(way[block * 8 + 1 : block * 8 + 8], dir), lambda z: z[1] * z[2])) AS seen FROM d, refs),
  b AS (SELECT t, own, seen, row_number() OVER (PARTITION BY t, block ORDER BY round(own, 9) DESC, ref) AS place FROM s),
  u AS (SELECT t, sum(own) AS own, sum(seen) AS seen FROM b WHERE place = 1 GROUP BY t),
  f AS (SELECT d.t, r, sqrt({dot('edge', 'edge')}) AS edge_len, sqrt({dot('way', 'way')}) AS way_len, {dot('edge', 'way')} AS inner_product, own, seen FROM d JOIN u USING (t)),
  y AS (SELECT t, r, edge_len, way_len, own / edge_len AS cos_own, seen / way_len AS cos_target, inner_product / (edge_len * way_len) AS cos_exact FROM f)"""
_WITH = f"WITH {_REFS}, {_TRIPLES}, {_PROFILE}"


def triples(spark, d):
    """(q_id, x_id, p, q, x, r): every vector as target, its fifth neighbour as pivot, the pivot's neighbours, and the target's twelfth distance as rim."""
    edges, emb = knn_graph(spark, d)
    emb = checkpoint(emb)
    order = F.row_number().over(E.Window.partitionBy("src").orderBy("edge_len", "dst"))
    ranked = checkpoint(edges.withColumn("rank", order))
    a = ranked.where("rank = 5").select(F.col("src").alias("q_id"), F.col("dst").alias("p_id"))
    z = ranked.where("rank = 12").select(F.col("src").alias("q_id"), F.col("edge_len").alias("r"))
    b = ranked.select(F.col("src").alias("p_id"), F.col("dst").alias("x_id"))
    rows = a.join(z, "q_id").join(b, "p_id").where("x_id != q_id")
    for name in ("p", "q", "x"):
        rows = rows.join(emb.select(F.col("vec_id").alias(f"{name}_id"), F.col("embedding").alias(name)), f"{name}_id")
    return rows.select("q_id", "x_id", "p", "q", "x", "r")


def profiled(spark, d):
    """The triples' lengths and cosines with the deterministic directions, and the rim."""
    return P.profile_triples(triples(spark, d), P.walsh_references(spark, DIM, BLOCKS, REFS), DIM, BLOCKS)


@BOOK.add(
    "m01_hadamard_rotation",
    f"""SELECT vec_id, round(sqrt({dot('h', 'h')}), 6) AS norm, round(h[1], 6) AS first, round(h[64], 6) AS last FROM (SELECT vec_id, list_transform(range(0, 64), lambda i:
    list_sum(list_transform(range(0, 64), lambda j: (CASE WHEN bit_count(CAST(i & j AS BIGINT)) % 2 = 0 THEN 0.125 ELSE -0.125 END) * CAST(embedding[j + 1] AS DOUBLE)))) AS h FROM embeddings)""",
)
def m01(spark, d):
    """Rotation by a Walsh-Hadamard matrix in columns."""
    row = lambda i: F.aggregate(F.transform("embedding", lambda v, j: P.walsh_sign(i, j) * 0.125 * v.cast("double")), F.lit(0.0), lambda s, v: s + v)
    turned = C.embeddings(spark, d).select("vec_id", F.transform(F.sequence(F.lit(0), F.lit(63)), row).alias("h"))
    norm = F.sqrt(F.aggregate("h", F.lit(0.0), lambda s, v: s + v * v))
    return turned.select("vec_id", F.round(norm, 6).alias("norm"), F.round(F.get("h", 0), 6).alias("first"), F.round(F.get("h", 63), 6).alias("last"))


@BOOK.add("m01_random_rotation")
def m01b(spark, d):
    """Rotation by a random orthogonal matrix in Arrow batches; lengths stay."""
    import pyarrow as pa

    from ..sources.session import ship

    ship(spark)
    turn = P.orthogonal(DIM, 17)

    def work(batches):
        for b in batches:
            if b.num_rows:
                x = np.asarray(b.column(1).flatten(), dtype=np.float32).reshape(b.num_rows, -1)
                y = x @ turn
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(y), type=pa.list_(pa.float32())), pa.array(np.abs(np.linalg.norm(y, axis=1) - np.linalg.norm(x, axis=1)).astype(np.float64))], ["vec_id", "embedding", "drift"])

    return C.embeddings(spark, d).mapInArrow(work, "vec_id bigint, embedding array<float>, drift double")


@BOOK.add("m02_block_split", "SELECT vec_id, CAST(b AS INTEGER) AS block, round(list_sum(list_transform(embedding[b * 8 + 1 : b * 8 + 8], lambda v: CAST(v AS DOUBLE) * v)), 6) AS sq FROM embeddings, (SELECT unnest(range(0, 8)) AS b)")
def m02(spark, d):
    cut = C.embeddings(spark, d).select("vec_id", F.posexplode(P.split_blocks(F.col("embedding"), BLOCKS, DIM)).alias("block", "part"))
    return cut.select("vec_id", "block", F.round(F.aggregate("part", F.lit(0.0), lambda s, v: s + v.cast("double") * v), 6).alias("sq"))


@BOOK.add(
    "m03_reference_family",
    f"""WITH {_REFS}, s AS (SELECT vec_id, block, ref, list_sum(list_transform(list_zip(embedding[block * 8 + 1 : block * 8 + 8], dir), lambda z: CAST(z[1] AS DOUBLE) * z[2])) AS own FROM embeddings, refs),
    b AS (SELECT block, ref, row_number() OVER (PARTITION BY vec_id, block ORDER BY round(own, 9) DESC, ref) AS place FROM s), n AS (SELECT block, ref, count(*) AS chosen FROM b WHERE place = 1 GROUP BY 1, 2)
    SELECT block, ref, CAST(j - 1 AS INTEGER) AS pos, CAST(dir[j] AS DOUBLE) AS v, coalesce(chosen, 0) AS chosen FROM refs LEFT JOIN n USING (block, ref), (SELECT unnest(range(1, 9)) AS j)""",
)
def m03(spark, d):
    """The directions of each block, and how many vectors choose each: the one with the largest inner product, the first of equal ones."""
    refs = P.walsh_references(spark, DIM, BLOCKS, REFS)
    chosen = P.chosen_references(C.embeddings(spark, d), refs, DIM, BLOCKS).groupBy("block", "ref").agg(F.count("*").alias("chosen"))
    each = refs.select("block", "ref", F.posexplode("dir").alias("pos", "v"))
    return each.join(F.broadcast(chosen), ["block", "ref"], "left").select("block", "ref", "pos", "v", F.coalesce("chosen", F.lit(0)).alias("chosen"))  # a row a direction


@BOOK.add("m05_edge_profile", _WITH + " SELECT t.q AS q_id, t.x AS x_id, round(edge_len, 6) AS edge_len, round(cos_own, 6) AS cos_own, round(cos_target, 6) AS cos_target FROM y")
def m05(spark, d):
    r = lambda c: F.round(c, 6).alias(c)
    return profiled(spark, d).select("q_id", "x_id", r("edge_len"), r("cos_own"), r("cos_target"))


@BOOK.add("m07_angle_estimate", _WITH + " SELECT t.q AS q_id, t.x AS x_id, round(cos_target / cos_own, 6) AS estimate, round(cos_exact, 6) AS cos_exact FROM y")
def m07(spark, d):
    return profiled(spark, d).select("q_id", "x_id", F.round(G.estimate_cosine(F.col("cos_target"), F.col("cos_own")), 6).alias("estimate"), F.round("cos_exact", 6).alias("cos_exact"))


def _stats(spark, d):
    c = F.col
    return profiled(spark, d).select("*", G.gate_and_screen(c("edge_len"), c("way_len"), c("r"), c("cos_target"), c("cos_own")).alias("s"))


_GATE = "cos_target / cos_own - (edge_len * edge_len + way_len * way_len - r * r) / (2 * edge_len * way_len)"
_SCREEN = "cos_target / cos_own - edge_len / (2 * way_len)"


@BOOK.add("m09_gate", _WITH + f" SELECT t.q AS q_id, t.x AS x_id, round({_GATE}, 6) AS gate, {_GATE} >= 0 AS passed FROM y")
def m09(spark, d):
    return _stats(spark, d).select("q_id", "x_id", F.round("s.gate", 6).alias("gate"), (F.col("s.gate") >= 0).alias("passed"))


@BOOK.add("m10_gate_threshold", _WITH + " SELECT t.q AS q_id, t.x AS x_id, round((edge_len * edge_len + way_len * way_len - r * r) / (2 * edge_len * way_len), 6) AS tau, round(edge_len / (2 * way_len), 6) AS delta FROM y")
def m10(spark, d):
    c = F.col
    return profiled(spark, d).select("q_id", "x_id", F.round(G.gate_threshold(c("edge_len"), c("way_len"), c("r")), 6).alias("tau"), F.round(G.screen_threshold(c("edge_len"), c("way_len")), 6).alias("delta"))


@BOOK.add("m20_screen", _WITH + f" SELECT t.q AS target, round(max({_SCREEN}), 6) AS stat, max({_SCREEN}) < 0 AS survives FROM y GROUP BY 1")
def m20(spark, d):
    one = _stats(spark, d).groupBy(F.col("q_id").alias("target")).agg(G.screen_stat(F.col("s.screen")).alias("v"))
    return one.select("target", F.round("v", 6).alias("stat"), (F.col("v") < 0).alias("survives"))


@BOOK.add("m21_shared_scan", _WITH + f" SELECT t.q AS q_id, t.x AS x_id, round({_GATE}, 6) AS gate, round({_SCREEN}, 6) AS screen FROM y")
def m21(spark, d):
    return _stats(spark, d).select("q_id", "x_id", F.round("s.gate", 6).alias("gate"), F.round("s.screen", 6).alias("screen"))


@BOOK.add(
    "a13_gate_rates",
    _WITH + f", g AS (SELECT {_GATE} >= 0 AS p, round(cos_exact - (edge_len * edge_len + way_len * way_len - r * r) / (2 * edge_len * way_len), 9) >= 0 AS q FROM y) SELECT count(*) AS n, round(avg(CAST(p AS INTEGER)), 6) AS pass_ratio, round(avg(CASE WHEN q THEN CAST(p AS INTEGER) END), 6) AS pass_if_true, round(avg(CASE WHEN NOT q THEN 1 - CAST(p AS INTEGER) END), 6) AS reject_if_false FROM g",
)
def a13(spark, d):
    c = F.col
    rows = _stats(spark, d).select(F.col("s.gate").alias("stat"), (F.round(c("cos_exact") - G.gate_threshold(c("edge_len"), c("way_len"), c("r")), 9) >= 0).alias("truth"))
    out = M.confusion(rows, "stat", "truth")
    return out.select("n", *[F.round(x, 6).alias(x) for x in ("pass_ratio", "pass_if_true", "reject_if_false")])


@BOOK.add(
    "a14_screen_rates",
    _WITH + f", g AS (SELECT t.q AS k, max({_SCREEN}) AS stat, bool_or(cos_exact >= edge_len / (2 * way_len)) AS q FROM y GROUP BY 1) SELECT count(*) AS n, round(avg(CAST(stat >= 0 AS INTEGER)), 6) AS pass_ratio, round(avg(CASE WHEN q THEN CAST(stat >= 0 AS INTEGER) END), 6) AS pass_if_true, round(avg(CASE WHEN NOT q THEN CAST(stat < 0 AS INTEGER) END), 6) AS reject_if_false FROM g",
)
def a14(spark, d):
    c = F.col
    rows = _stats(spark, d).withColumn("near", c("cos_exact") >= G.screen_threshold(c("edge_len"), c("way_len")))
    one = rows.groupBy("q_id").agg(F.max("s.screen").alias("stat"), F.bool_or("near").alias("truth"))
    out = M.confusion(one, "stat", "truth")
    return out.select("n", *[F.round(x, 6).alias(x) for x in ("pass_ratio", "pass_if_true", "reject_if_false")])


@BOOK.add(
    "a15_estimator_error",
    _WITH + ", g AS (SELECT cos_target / cos_own AS e, cos_exact AS c FROM y) SELECT round(avg(e - c), 6) AS bias, round(sqrt(avg((e - c) * (e - c))), 6) AS rmse, round(corr(e, c), 6) AS corr, round(covar_samp(e, c), 6) AS covar, round(var_samp(e - c), 6) AS var FROM g",
)
def a15(spark, d):
    rows = profiled(spark, d).select(G.estimate_cosine(F.col("cos_target"), F.col("cos_own")).alias("estimate"), "cos_exact")
    return M.estimator_error(rows).select(*[F.round(x, 6).alias(x) for x in ("bias", "rmse", "corr", "covar", "var")])


def _error_sql(blocks: int, refs: int) -> str:
    family, profile = _family(blocks, refs)
    return (
        f"(WITH {family}, {_TRIPLES}, {profile}, g AS (SELECT cos_target / cos_own AS e, cos_exact AS c FROM y) "
        f"SELECT {blocks} AS blocks, {refs} AS refs, round(avg(e - c), 6) AS bias, round(sqrt(avg((e - c) * (e - c))), 6) AS rmse, round(corr(e, c), 6) AS corr FROM g)"
    )


_SWEEP = ((2, 16), (4, 16), (8, 8), (8, 16))


@BOOK.add("a15_error_by_blocks_and_references", " UNION ALL ".join(_error_sql(b, r) for b, r in _SWEEP))
def a15b(spark, d):
    """The estimate's error over numbers of blocks and of references: it falls with either."""
    rows = checkpoint(triples(spark, d))
    out = None
    for blocks, refs in _SWEEP:
        found = P.profile_triples(rows, P.walsh_references(spark, DIM, blocks, refs), DIM, blocks)
        one = M.estimator_error(found.select(G.estimate_cosine(F.col("cos_target"), F.col("cos_own")).alias("estimate"), "cos_exact"))
        one = one.select(F.lit(blocks).alias("blocks"), F.lit(refs).alias("refs"), *[F.round(x, 6).alias(x) for x in ("bias", "rmse", "corr")])
        out = one if out is None else out.unionByName(one)
    return out


_UNIT = f"""v AS (SELECT list_transform(edge, lambda z: z / sqrt({dot('edge', 'edge')})) AS edge, list_transform(way, lambda z: z / sqrt({dot('way', 'way')})) AS way FROM d)"""


@BOOK.add(
    "a16_block_balance",
    f"WITH {_TRIPLES}, d AS (SELECT t, list_transform(list_zip(x, p), lambda z: CAST(z[1] AS DOUBLE) - z[2]) AS edge, list_transform(list_zip(q, p), lambda z: CAST(z[1] AS DOUBLE) - z[2]) AS way FROM t), {_UNIT}, "
    f"c AS (SELECT edge, way, edge[l * 8 + 1 : l * 8 + 8] AS a, way[l * 8 + 1 : l * 8 + 8] AS b FROM v, (SELECT unnest(range(0, 8)) AS l)) "
    f"SELECT round(max(greatest(abs(sqrt(8) * sqrt({dot('a', 'a')}) - 1), abs(sqrt(8) * sqrt({dot('b', 'b')}) - 1), abs(8 * {dot('a', 'b')} - {dot('edge', 'way')}))), 6) AS eta FROM c",
)
def a16(spark, d):
    rows = triples(spark, d).select(V.normalise(V.subtract("x", "p")).alias("edge"), V.normalise(V.subtract("q", "p")).alias("way"))
    return M.block_balance(rows, BLOCKS).select(F.round("eta", 6).alias("eta"))


# --- graphs -------------------------------------------------------------------------


def _search(params: Params, ef: int, k: int = 10, **options):
    """Build over all of ``embeddings``, search every id divisible by 100, with the counters."""

    def query(spark, d):
        emb, q = native(spark, d)
        return rounded(build_index(emb, params).search(q, k, ef, **options))

    return query


_EXACT10 = knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 10)


@BOOK.add("m26_search_whole_graph", _EXACT10)
def m26(spark, d):
    """A search as wide as the graph, gate off: the exact answers (distances measured again in doubles)."""
    emb, q = native(spark, d)
    hits = build_index(emb, B.no_gate_params(DIM)).search(q, 20, max(64, emb.count()))
    return _measured_again(hits, emb, q)


BOOK.add("m12_queue_threshold")(_search(Params(DIM, threshold="queue", rings=False), 64))
BOOK.add("m15_ringed_gate")(_search(Params(DIM), 64))
BOOK.add("m11_cosine_metric")(_search(Params(DIM, metric="cosine"), 64))
BOOK.add("m28_throughput_preset")(_search(Params.throughput(DIM), 128))
BOOK.add("m29_compact_preset")(_search(Params.compact(DIM), 128))
BOOK.add("b02_hnsw")(_search(B.hnsw_params(DIM), 64))
BOOK.add("b10_hnsw_plugin_test")(_search(B.plugin_params(DIM), 64))
BOOK.add("b12_gate_only")(_search(B.gate_only_params(DIM), 64))
BOOK.add("b13_no_gate")(_search(B.no_gate_params(DIM), 64))


# A search as wide as its graph must give the exact answers, whatever the method.


def _measured_again(hits, emb, q, k=10):
    """The hits' distances in doubles, and the k first by them; searches give twice as many, as floats may swap neighbours."""
    again = hits.select("qid", "vec_id").join(emb, "vec_id").join(q, "qid").select("qid", "vec_id", V.l2("embedding", "qvec").alias("dist"))
    return rounded(E.top_k(again, k).select("qid", "rank", "vec_id", "dist"))


#: Vectors of a shard of these builds: each shard is built by a task, and the search of all of them is as exact.
WHOLE_SHARD = 8192


def whole_shards(n: int, least: int = 1) -> int:
    return max(least, -(-n // WHOLE_SHARD))


def _whole(params: Callable[[int], Params], shards: int = 1):
    def query(spark, d):
        """As wide as the graph, with a working set of that size: the exact answers."""
        emb, q = native(spark, d)
        n = emb.count()
        return _measured_again(build_index(emb, params(n), shards=whole_shards(n, shards)).search(q, 20, n), emb, q)

    return query


def _whole_method(kind: str, **options):
    def query(spark, d):
        """All cells, or a beam as wide as the graph, all reranked: the exact answers."""
        emb, q = native(spark, d)
        n = emb.count()
        given = tuple((k, v(n) if callable(v) else v) for k, v in options.items())
        hits, _ = X.run(emb, q, [X.Method(kind, kind, Params(DIM), given)], [(20, 8 * n)], whole_shards(n))
        return _measured_again(hits, emb, q)

    return query


for _name, _params in {
    "b02_hnsw_whole": lambda n: B.hnsw_params(DIM),
    "b10_plugin_whole": lambda n: B.plugin_params(DIM),
    "b12_gate_only_whole": lambda n: B.gate_only_params(DIM),
    "m12_queue_threshold_whole": lambda n: Params(DIM, threshold="queue", rings=False),
    "m15_ringed_gate_whole": lambda n: Params(DIM, work=n),
    "m28_throughput_whole": lambda n: Params.throughput(DIM, work=n),
    "m29_compact_whole": lambda n: Params.compact(DIM, work=n, half=False),
    "m11_cosine_whole": lambda n: Params(DIM, metric="cosine", work=n),
    "m13_many_rounds_whole": lambda n: Params(DIM, work=32, gate=False),
}.items():
    BOOK.add(_name, _EXACT10)(_whole(_params))
BOOK.add("sharded_whole", _EXACT10)(_whole(lambda n: Params(DIM, work=n), shards=4))
BOOK.add("b03_vamana_whole", _EXACT10)(_whole_method("vamana"))
BOOK.add("b04_nsg_whole", _EXACT10)(_whole_method("nsg"))
BOOK.add("b08_quantised_graph_whole", _EXACT10)(_whole_method("qgraph"))
for _kind, _label in (("pq", "b05_ivfpq"), ("aniso", "b06_anisotropic"), ("scalar", "b07_scalar_codes")):
    BOOK.add(f"{_label}_cells_whole", _EXACT10)(_whole_method(_kind, rerank=lambda n: n))


@BOOK.add("m27_insertion_whole", _EXACT10)
def m27b(spark, d):
    """A third of the corpus built, the rest inserted in batches without a shuffle of the index: a full search is exact."""
    emb, q = native(spark, d)
    n = emb.count()
    index = build_index(emb.where("vec_id % 3 = 0"), Params(DIM, work=n), shards=3)
    for part in (1, 2):
        index = insert_batch(index, emb.where(f"vec_id % 3 = {part}"))
    return _measured_again(index.search(q, 20, n), emb, q)


@BOOK.add("m24_screen_scope")
def m24(spark, d):
    """The screen over the out-neighbours of a new node against all visited nodes, on a corpus with hubs: screened edges and starved nodes."""
    corpus = materialise(C.doc_vec(spark, d, 384), "corpus")
    out = None
    for scope in ("out", "visited"):
        index = build_index(corpus, Params(384, scope=scope))
        edges = checkpoint(index.edges())
        degrees = M.in_degrees(edges, index.nodes())
        one = degrees.agg(F.lit(scope).alias("scope"), F.count("*").alias("nodes"), F.count_if(F.col("in_degree") <= 1).alias("at_most_one"), F.avg("in_degree").alias("mean"))
        one = one.crossJoin(F.broadcast(edges.agg(F.count_if(F.col("origin") == "screen").alias("screened"))))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


@BOOK.add("a11_visited_nodes")
def a11(spark, d):
    """Visited nodes of equally good searches against M log n, over growing parts of the lines."""
    lines = materialise(C.doc_line_vec(spark, d, 96), "corpus")

    def one(share: int) -> DataFrame:
        part = lines if share == 1 else materialise(lines.where(f"vec_id % {share} = 0"), "part")
        n, queries = part.count(), materialise(C.native_queries(part), "queries")
        runs = X.curve(spark, part, queries, [X.Method("hnsw", "graph", B.hnsw_params(96))], 10, [16, 32, 64], exclude_self=True, stored=True)[0]
        best = runs.where("recall >= 0.9").orderBy("n_visited").limit(1)
        return best.select(F.lit(n).alias("n"), "ef", "recall", "n_visited", "n_exact", (F.col("n_exact") / (16 * math.log(n))).alias("over_m_log_n"))

    # the whole takes the longest and begins
    found = X.together(spark, [lambda share=share: one(share) for share in (1, 2, 4, 8)])
    return reduce(DataFrame.unionByName, reversed(found))


@BOOK.add("m13_ring_sizes")
def m13(spark, d):
    """The working set's size against cost and recall; as large as the search, it is the single queue."""
    emb, q = native(spark, d)
    methods = [X.Method(f"work_{w}", "graph", Params(DIM, work=w, ef_build=64)) for w in (8, 16, 32, 64)]
    return X.curve(spark, emb, q, methods, 10, [64])[0]


@BOOK.add("m23_pending_and_origins")
def m23(spark, d):
    """Edges by how they came: out, in, or verified from the screen."""
    emb, _ = native(spark, d)
    return build_index(emb, Params(DIM)).edges().groupBy("origin").agg(F.count("*").alias("edges"))


@BOOK.add("m25_build_rows", "SELECT count(*) AS nodes, count(DISTINCT vec_id) AS ids, true AS degree_ok, true AS no_loops FROM embeddings")
def m25(spark, d):
    """Every vector is a node once; no node exceeds its cap; no edge leads to its own source."""
    emb, _ = native(spark, d)
    params = Params(DIM)
    rows = build_index(emb, params).rows
    return rows.select("vec_id", (F.size("adj") <= params.cap).alias("ok"), (~F.array_contains("adj", F.col("place"))).alias("free")).agg(
        F.count("*").alias("nodes"), F.countDistinct("vec_id").alias("ids"), F.bool_and("ok").alias("degree_ok"), F.bool_and("free").alias("no_loops")
    )


@BOOK.add("m25_copies_folded", "SELECT count(*) AS vectors, count(DISTINCT embedding) AS nodes FROM (" + C.hash_vectors_sql(C.DOC_TOKENS_SQL, 128) + ")")
def m25b(spark, d):
    """Copies share a node; nodes and copies together are all vectors."""
    index = build_index(C.doc_vec(spark, d, 128), Params(128))
    return index.rows.agg((F.count("*") + F.sum(F.size("copies"))).alias("vectors"), F.count("*").alias("nodes"))


@BOOK.add("m27_online_insertion")
def m27(spark, d):
    """Half of the corpus built, the rest inserted in two batches, then searched."""
    emb, q = native(spark, d)
    index = build_index(emb.where("vec_id % 2 = 0"), Params(DIM))
    for part in (1, 3):
        index = insert_batch(index, emb.where(f"vec_id % 4 = {part}"))
    return rounded(index.search(q, 10, 64))


@BOOK.add("m30_half_floats")
def m30(spark, d):
    """Two-byte against four-byte vectors: recall, cost and bytes."""
    emb, q = native(spark, d)
    truth = E.exact_knn(emb, q, 10)
    out = None
    for name, params in (("float", Params(DIM)), ("half", Params(DIM, half=True))):
        index = build_index(emb, params)
        one = M.recall_at_k(index.search(q, 10, 64), truth, 10).crossJoin(F.broadcast(index.size_report().agg(F.sum("bytes").alias("bytes"))))  # one row each
        one = one.select(F.lit(name).alias("stored"), "recall", "bytes")
        out = one if out is None else out.unionByName(one)
    return out


@BOOK.add("m31_tuning_blocks_and_references")
def m31(spark, d):
    """Gate cost and recall over numbers of blocks and of references a block."""
    emb, q = native(spark, d)
    methods = [X.Method(f"L{b}_m{r}", "graph", Params(DIM, blocks=b, refs_per_block=r)) for b in (4, 8, 16) for r in (16, 64)]
    return X.curve(spark, emb, q, methods, 10, [64])[0]


def _quantised(kind: str):
    def query(spark, d):
        emb, q = native(spark, d)
        emb = materialise(emb, "corpus")
        return rounded(Z.build_quantised(emb, kind, nlist=16, parts=16).search(q, 10, nprobe=16))

    return query


BOOK.add("b05_ivfpq")(_quantised("pq"))
BOOK.add("b06_anisotropic")(_quantised("aniso"))
BOOK.add("b07_scalar_codes")(_quantised("scalar"))


def _single(method: X.Method, ef: int = 64):
    def query(spark, d):
        emb, q = native(spark, d)
        return X.curve(spark, emb, q, [method], 10, [ef])[0]

    return query


BOOK.add("b03_vamana")(_single(X.Method("vamana", "vamana", Params(DIM))))
BOOK.add("b04_nsg")(_single(X.Method("nsg", "nsg", Params(DIM))))
BOOK.add("b08_quantised_graph")(_single(X.Method("qgraph", "qgraph", Params(DIM)), 128))


@BOOK.add("b09_accumulator_overflow")
def b09(spark, d):
    """The quantised graph with 16-bit sums over dimensions: recall falls where they overflow."""
    out = None
    for dim in (384, 1536, 3072):
        corpus, queries = C.doc_vec(spark, d, dim), C.bench_vec(spark, d, dim).select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
        methods = [X.Method(a, "qgraph", Params(dim), (("accumulator", a),)) for a in ("i32", "u16")]
        one = X.curve(spark, corpus, queries, methods, 10, [64])[0].withColumn("dim", F.lit(dim))
        out = one if out is None else out.unionByName(one)
    return out


@BOOK.add("a08_index_size")
def a08(spark, d):
    emb, _ = native(spark, d)
    sizes = [build_index(emb, p).size_report().withColumn("preset", F.lit(p.preset)) for p in (Params.throughput(DIM), Params.compact(DIM), B.hnsw_params(DIM))]
    return sizes[0].unionByName(sizes[1]).unionByName(sizes[2])


@BOOK.add("a09_cost_counters")
def a09(spark, d):
    """Mean counters of a search and the share of checked neighbours that passed."""
    emb, q = native(spark, d)
    return M.cost_report(build_index(emb, Params.throughput(DIM)).search(q, 10, 64).withColumn("method", F.lit("throughput")), ["method"])


@BOOK.add("a02_throughput")
def a02(spark, d):
    """Queries a second by the driver's clock, after a run that warms up, to a sink that keeps nothing: every vector asks."""
    import time

    emb, _ = native(spark, d)
    asked = materialise(emb.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec")), "queries")
    n, out = asked.count(), []
    for name, params in (("throughput", Params.throughput(DIM)), ("compact", Params.compact(DIM)), ("hnsw", B.hnsw_params(DIM, m_links=32, ef_build=128))):
        index = build_index(emb, params, shards=4)
        for run in range(2):
            began = time.perf_counter()
            index.search(asked, 10, 64).write.format("noop").mode("overwrite").save()
        seconds = time.perf_counter() - began
        out.append((name, n, seconds, n / seconds))
    return spark.createDataFrame(out, "method string, queries bigint, seconds double, qps double")


@BOOK.add("a17_starved_nodes")
def a17b(spark, d):
    """In-degrees with and without the screen on a corpus with hubs."""
    corpus = materialise(C.doc_vec(spark, d, 384), "corpus")
    out = None
    for name, on in (("without", False), ("with", True)):
        index = build_index(corpus, Params(384, screen=on))
        degrees = M.in_degrees(index.edges(), index.nodes())
        one = degrees.agg(
            F.lit(name).alias("screen"),
            F.count("*").alias("nodes"),
            F.count_if(F.col("in_degree") == 0).alias("none"),
            F.count_if(F.col("in_degree") <= 1).alias("at_most_one"),
            F.avg("in_degree").alias("mean"),
        )
        out = one if out is None else out.unionByName(one)
    return out


@BOOK.add("a17_unreachable")
def a17c(spark, d):
    """Nodes that no path reaches, with and without the screen, on a corpus with hubs and few links."""
    corpus = materialise(C.doc_vec(spark, d, 384), "corpus")
    out = None
    for name, on in (("without", False), ("with", True)):
        index = build_index(corpus, Params(384, screen=on, m_links=4, ef_build=16))
        edges, nodes = checkpoint(index.edges().select("src", "dst")), checkpoint(index.nodes().select("vec_id", "entry"))
        lost = M.unreachable(edges, nodes, nodes.where("entry"))
        one = lost.agg(F.lit(name).alias("screen"), F.count("*").alias("unreachable"))
        out = one if out is None else out.unionByName(one)
    return out


@BOOK.add(
    "u07_reachable",
    f"""WITH RECURSIVE e AS ({_GRAPH}), r AS (SELECT CAST(0 AS BIGINT) AS vec_id UNION SELECT e.vec_id FROM r JOIN e ON e.qid = r.vec_id AND e.rank <= 2)
    SELECT vec_id FROM embeddings WHERE vec_id NOT IN (SELECT vec_id FROM r)""",
)
def u07(spark, d):
    """What the two nearest links of each node do not reach from node 0: a loop over tables here, a recursion in SQL."""
    edges, emb = knn_graph(spark, d)
    near = E.Window.partitionBy("src").orderBy("edge_len", "dst")
    two = checkpoint(edges.withColumn("rank", F.row_number().over(near)).where("rank <= 2").select("src", "dst"))
    return M.unreachable(two, emb, emb.where("vec_id = 0"))


@BOOK.add("m32_ablation_native")
def m32(spark, d):
    emb, q = native(spark, d)
    return X.curve(spark, emb, q, X.ablation_methods(DIM), 10, [32, 64, 128])[0]


@BOOK.add("a21_cost_model_runs")
def a21(spark, d):
    """Modelled against counted operations of the ablation arms."""
    emb, q = native(spark, d)
    runs = X.curve(spark, emb, q, X.ablation_methods(DIM), 10, [64])[0]
    p = Params.throughput(DIM)
    counted = F.col("n_checked") * p.blocks + F.col("n_exact") * DIM
    return runs.select("method", "recall", M.cost_model("n_visited", p.cap, p.blocks, "pass_ratio", DIM).alias("modelled"), counted.alias("counted"))


@BOOK.add("sharded_search")
def sharded(spark, d):
    """The corpus in several shards, all probed: recall and cost against one shard."""
    emb, q = native(spark, d)
    truth = checkpoint(E.exact_knn(emb, q, 10))
    out = None
    for shards in (1, 4):
        index = build_index(emb, Params(DIM, shard_size=-(-emb.count() // shards)))
        hits = checkpoint(index.search(q, 10, 64).withColumn("method", F.lit(f"shards {shards}")))
        one = M.recall_at_k(hits, truth, 10, ["method"]).join(M.cost_report(hits, ["method"]), "method")
        out = one if out is None else out.unionByName(one)
    return out

