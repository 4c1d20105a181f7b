"""Vector functions, derived corpora, exact search and its kin; all with SQL."""

from __future__ import annotations

from pyspark.sql import Window, functions as F

from ..functions import vectors as V
from ..operators import exact as E
from ..operators import measures as M
from ..operators import occlude as O
from ..sources import corpora as C
from ..sources.session import checkpoint
from ..sources.tables import load
from .base import Book

BOOK = Book()
D = 6  # decimals of a distance

# --- SQL pieces ---------------------------------------------------------------------

_L2 = "sqrt(list_sum(list_transform(list_zip({a}, {b}), lambda z: (CAST(z[1] AS DOUBLE) - z[2]) * (CAST(z[1] AS DOUBLE) - z[2]))))"
_DOT = "list_sum(list_transform(list_zip({a}, {b}), lambda z: CAST(z[1] AS DOUBLE) * z[2]))"


def l2(a, b):
    return _L2.format(a=a, b=b)


def dot(a, b):
    return _DOT.format(a=a, b=b)


NATIVE_Q = "SELECT vec_id AS qid, embedding AS qvec FROM embeddings WHERE vec_id % 100 = 0"


def knn_sql(corpus: str, queries: str, k: int, dist: str = None, where: str = "") -> str:
    dist = dist or l2("embedding", "qvec")
    return f"""SELECT qid, CAST(rank AS INTEGER) AS rank, vec_id, round(dist, {D}) AS dist FROM (
      SELECT qid, vec_id, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, vec_id) AS rank FROM (
        SELECT qid, vec_id, {dist} AS dist FROM ({corpus}) c, ({queries}) q {where})) WHERE rank <= {k}"""


def rounded(df):
    return df.withColumn("dist", F.round("dist", D))


def native(spark, d):
    emb = C.embeddings(spark, d)
    return emb, C.native_queries(emb)


# --- functions ----------------------------------------------------------------------


@BOOK.add(
    "f01_vector_functions",
    f"""SELECT a.vec_id, round({l2('a.embedding', 'b.embedding')}, 6) AS l2, round({dot('a.embedding', 'b.embedding')}, 6) AS dot,
    round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: abs(CAST(z[1] AS DOUBLE) - z[2]))), 6) AS l1,
    round(list_max(list_transform(list_zip(a.embedding, b.embedding), lambda z: abs(CAST(z[1] AS DOUBLE) - z[2]))), 6) AS linf,
    round({dot('a.embedding', 'b.embedding')} / sqrt({dot('a.embedding', 'a.embedding')} * {dot('b.embedding', 'b.embedding')}), 6) AS cosine
    FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1""",
)
def f01(spark, d):
    emb = C.embeddings(spark, d)
    nxt = emb.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    r = lambda c, n: F.round(c, 6).alias(n)
    return emb.join(nxt, "vec_id").select(
        "vec_id",
        r(V.l2("embedding", "other"), "l2"),
        r(V.dot("embedding", "other"), "dot"),
        r(V.l1("embedding", "other"), "l1"),
        r(V.linf("embedding", "other"), "linf"),
        r(V.cosine_similarity("embedding", "other"), "cosine"),
    )


@BOOK.add("f01_vector_arithmetic", f"SELECT vec_id, round(sqrt({dot('embedding', 'embedding')}), 6) AS norm, round(list_sum(list_transform(embedding, lambda v: 2.0 * CAST(v AS DOUBLE) + v)), 6) AS sums FROM embeddings")
def f01b(spark, d):
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda s, v: s + v)
    return C.embeddings(spark, d).select("vec_id", F.round(V.norm("embedding"), 6).alias("norm"), F.round(total(V.add(V.scale("embedding", 2.0), F.col("embedding"))), 6).alias("sums"))


@BOOK.add("u01_sql_functions", f"SELECT qid, vec_id, round({l2('embedding', 'qvec')}, 6) AS dist, round({dot('embedding', 'qvec')}, 6) AS inner_product FROM embeddings, ({NATIVE_Q})")
def u01(spark, d):
    V.register(spark)
    emb, q = native(spark, d)
    emb.createOrReplaceTempView("corpus_view")
    q.createOrReplaceTempView("query_view")
    return spark.sql("SELECT qid, vec_id, round(vec_l2(embedding, qvec), 6) AS dist, round(vec_dot(embedding, qvec), 6) AS inner_product FROM corpus_view CROSS JOIN query_view q")


# --- corpora ------------------------------------------------------------------------


def _corpus(name, build, sql):
    @BOOK.add(name, f"SELECT vec_id, CAST(i - 1 AS INTEGER) AS pos, round(CAST(embedding[i] AS DOUBLE), 5) AS v FROM ({sql}) c, (SELECT unnest(range(1, 3073)) AS i) WHERE i <= len(embedding) AND embedding[i] <> 0")
    def query(spark, d):
        each = build(spark, d).select("vec_id", F.posexplode("embedding").alias("pos", "x"))
        return each.where("x != 0").select("vec_id", "pos", F.round(F.col("x").cast("double"), 5).alias("v"))

    return query


_corpus("corpus_documents_384", lambda s, d: C.doc_vec(s, d, 384), C.hash_vectors_sql(C.DOC_TOKENS_SQL, 384))
_corpus("corpus_benchmark_384", lambda s, d: C.bench_vec(s, d, 384), C.hash_vectors_sql(C.BENCH_TOKENS_SQL, 384))
_corpus("corpus_pages_512", lambda s, d: C.page_vec(s, d, 512), C.hash_vectors_sql(C.PAGE_TOKENS_SQL, 512))
_corpus("corpus_conversations_384", lambda s, d: C.conv_vec(s, d, 384), C.hash_vectors_sql(C.CONV_TOKENS_SQL, 384))
_corpus("corpus_lines_96", lambda s, d: C.doc_line_vec(s, d, 96), C.hash_vectors_sql(C.LINE_TOKENS_SQL, 96))
_corpus("corpus_lineitem_96", lambda s, d: C.line_vec(s, d, 96), C.hash_vectors_sql(C.LINEITEM_TOKENS_SQL, 96))
_corpus("corpus_parts_150", lambda s, d: C.part_vec(s, d, 150), C.hash_vectors_sql(C.PART_TOKENS_SQL, 150))
_corpus("corpus_customers_96", lambda s, d: C.customer_vec(s, d, 96), C.hash_vectors_sql(C.CUSTOMER_TOKENS_SQL, 96))
_corpus("corpus_users_120", lambda s, d: C.user_vec(s, d), C.USER_VEC_SQL)


# --- exact search -------------------------------------------------------------------


@BOOK.add("b01_exact_knn", knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 10))
def b01(spark, d):
    emb, q = native(spark, d)
    return rounded(E.exact_knn(emb, q, 10, plan="sql"))


@BOOK.add("b01_exact_knn_blocks", knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 10))
def b01b(spark, d):
    emb, q = native(spark, d)
    return rounded(E.exact_knn(emb, q, 10, plan="blocks"))


_COS = f"1 - {dot('embedding', 'qvec')} / (sqrt({dot('embedding', 'embedding')}) * sqrt({dot('qvec', 'qvec')}))"


@BOOK.add("b01_exact_knn_cosine", knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 10, f"abs(round({_COS}, 9))"))
def b01c(spark, d):
    emb, q = native(spark, d)
    pairs = E.pairs(emb, q, 64).select("qid", "vec_id", F.abs(F.round(V.cosine_distance("embedding", "qvec"), 9)).alias("dist"))
    return rounded(E.top_k(pairs, 10).select("qid", "rank", "vec_id", "dist"))


@BOOK.add("b01_exact_knn_dot", knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 10, f"-{dot('embedding', 'qvec')}"))
def b01d(spark, d):
    emb, q = native(spark, d)
    return rounded(E.exact_knn(emb, q, 10, "dot"))


@BOOK.add("p03_filtered_pre", knn_sql("SELECT vec_id, embedding FROM embeddings WHERE label = 3", NATIVE_Q, 5))
def p03(spark, d):
    emb, q = native(spark, d)
    return rounded(E.filtered_knn(emb, q, 5, load(spark, d, "embeddings").where("label = 3").select("vec_id"), "pre"))


@BOOK.add("p03_filtered_post", knn_sql("SELECT vec_id, embedding FROM embeddings WHERE label = 3", NATIVE_Q, 5))
def p03b(spark, d):
    emb, q = native(spark, d)
    return rounded(E.filtered_knn(emb, q, 5, load(spark, d, "embeddings").where("label = 3").select("vec_id"), "post"))


@BOOK.add("p04_range_search", f"SELECT qid, vec_id, round(dist, {D}) AS dist FROM (SELECT qid, vec_id, {l2('embedding', 'qvec')} AS dist FROM embeddings, ({NATIVE_Q})) WHERE dist <= 1.25")
def p04(spark, d):
    emb, q = native(spark, d)
    return rounded(E.range_search(emb, q, 1.25))


_PART_Q = "SELECT vec_id AS qid, embedding AS qvec FROM ({}) WHERE vec_id % 100 = 0"


@BOOK.add("j12_knn_join", knn_sql("SELECT vec_id, embedding FROM embeddings", "SELECT vec_id AS qid, embedding AS qvec FROM embeddings", 3, where="WHERE vec_id <> qid"))
def j12(spark, d):
    emb = C.embeddings(spark, d)
    left = emb.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
    return rounded(E.exact_knn(emb, left, 3, plan="blocks", exclude_self=True))


@BOOK.add("j13_lateral_top_k", knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 4))
def j13(spark, d):
    emb, q = native(spark, d)
    emb.createOrReplaceTempView("corpus_view")
    q.createOrReplaceTempView("query_view")
    # Each query meets packs of vectors and takes four of each: pairs are neither sorted nor shuffled.
    packs = "SELECT collect_list(struct(vec_id, embedding)) AS pack FROM corpus_view GROUP BY vec_id DIV 256"
    dist = V.SQL_L2.replace("zip_with(a, b", "zip_with(v.embedding, q.qvec")
    out = spark.sql(
        f"""SELECT q.qid, t.vec_id, t.dist FROM ({packs}) p CROSS JOIN query_view q, LATERAL inline(slice(array_sort(transform(p.pack, v -> struct({dist} AS dist, v.vec_id AS vec_id))), 1, 4)) AS t(dist, vec_id)"""
    )
    return rounded(E.top_k(out, 4).select("qid", "rank", "vec_id", "dist"))


# --- measures over exact results ----------------------------------------------------


_NEAR30 = knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 30).replace(f"round(dist, {D})", "dist")


@BOOK.add(
    "a01_recall",
    f"""WITH t AS ({_NEAR30}), h AS (SELECT m, qid, dist, row_number() OVER (PARTITION BY m, qid ORDER BY dist, vec_id) AS rank FROM t, (SELECT unnest([2, 3, 5, 7]) AS m) WHERE vec_id % m <> 0),
    g AS (SELECT m, t.qid, count(h.qid) AS got FROM (SELECT qid, max(dist) AS far FROM t WHERE rank <= 10 GROUP BY 1) t CROSS JOIN (SELECT unnest([2, 3, 5, 7]) AS m)
      LEFT JOIN h USING (m, qid) WHERE h.qid IS NULL OR h.rank <= 10 GROUP BY 1, 2), w AS (SELECT m, qid, sum(CAST(h.dist <= far + 1e-6 AS INTEGER)) AS good FROM h JOIN (SELECT qid, max(dist) AS far FROM t WHERE rank <= 10 GROUP BY 1) USING (qid) WHERE rank <= 10 GROUP BY 1, 2)
    SELECT m, round(avg(coalesce(good, 0) / 10), 6) AS recall FROM g LEFT JOIN w USING (m, qid) GROUP BY 1""",
)
def a01(spark, d):
    """Recall of answers that miss every m-th id: what is left of the thirty nearest, against the ten nearest."""
    emb, q = native(spark, d)
    near = checkpoint(E.exact_knn(emb, q, 30, plan="blocks"))
    hits = near.drop("rank").join(F.broadcast(spark.createDataFrame([(m,) for m in (2, 3, 5, 7)], "m int")), F.col("vec_id") % F.col("m") != 0)  # four rows
    ranked = hits.withColumn("rank", F.row_number().over(Window.partitionBy("m", "qid").orderBy("dist", "vec_id")))
    return M.recall_at_k(ranked, near, 10, ["m"]).select("m", F.round("recall", 6).alias("recall"))


#: The parts as if they were runs: a brand's sizes and prices for a method's recalls and costs.
_RUNS = "SELECT p_brand AS method, p_size / 50.0::DOUBLE AS recall, p_retailprice AS n_exact FROM part"


def _runs(spark, d):
    return load(spark, d, "part").select(F.col("p_brand").alias("method"), (F.col("p_size") / 50.0).alias("recall"), F.col("p_retailprice").alias("n_exact"))


_CURVE = f"""c AS (SELECT method, recall, n_exact FROM (SELECT *, max(recall) OVER (PARTITION BY method ORDER BY n_exact, recall DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS best FROM ({_RUNS})) WHERE best IS NULL OR recall > best)"""
_AT = f"""{_CURVE}, l AS (SELECT method, recall, n_exact AS c, lead(recall) OVER w AS r2, lead(n_exact) OVER w AS c2 FROM c WINDOW w AS (PARTITION BY method ORDER BY recall, n_exact)),
  x AS (SELECT method, min(CASE WHEN recall >= 0.55 THEN c ELSE c + (c2 - c) * (0.55 - recall) / (r2 - recall) END) AS cost FROM l WHERE (recall <= 0.55 AND r2 >= 0.55) OR recall >= 0.55 GROUP BY 1)"""


@BOOK.add("a03_tradeoff_curve", f"WITH {_CURVE} SELECT method, round(recall, 6) AS recall, n_exact FROM c")
def a03(spark, d):
    return M.tradeoff_curve(_runs(spark, d)).select("method", F.round("recall", 6).alias("recall"), "n_exact")


@BOOK.add("a04_speedup", f"WITH {_AT} SELECT x.method, round(b.cost / x.cost, 6) AS speedup FROM x, (SELECT cost FROM x WHERE method = 'Brand#12') b")
def a04(spark, d):
    return M.speedup_at(_runs(spark, d), 0.55, "Brand#12").select("method", F.round("speedup", 6).alias("speedup"))


@BOOK.add("a05_recall_nines", f"SELECT method, round(recall, 6) AS recall, round(-log10(1 - recall), 6) AS nines FROM (SELECT DISTINCT method, recall FROM ({_RUNS})) WHERE recall < 1")
def a05(spark, d):
    runs = _runs(spark, d).select("method", "recall").distinct().where("recall < 1")
    return runs.select("method", F.round("recall", 6).alias("recall"), F.round(V.recall_nines("recall"), 6).alias("nines"))


@BOOK.add("a10_cost_report", "SELECT p_brand AS method, round(avg(p_size), 6) AS n_checked, round(sum(p_partkey % 7) / sum(p_size), 6) AS pass_ratio FROM part GROUP BY 1")
def a10(spark, d):
    p = load(spark, d, "part")
    counters = {c: F.lit(0) for c in ("n_exact", "n_visited", "n_fp", "n_fp_reused", "n_rounds")}
    hits = p.select(F.col("p_brand").alias("method"), F.col("p_partkey").alias("qid"), F.col("p_size").alias("n_checked"), (F.col("p_partkey") % 7).alias("n_pass")).withColumns(counters)
    return M.cost_report(hits, ["method"]).select("method", F.round("n_checked", 6).alias("n_checked"), F.round("pass_ratio", 6).alias("pass_ratio"))


@BOOK.add("a19_amortised_ratio", "SELECT o_orderpriority AS method, round(avg(o_totalprice) FILTER (WHERE o_orderstatus = 'O') / avg(o_totalprice) FILTER (WHERE o_orderstatus <> 'O'), 6) AS ratio FROM orders GROUP BY 1")
def a19(spark, d):
    o = load(spark, d, "orders")
    runs = o.select(F.col("o_orderpriority").alias("method"), F.when(F.col("o_orderstatus") == "O", "insert").otherwise("search").alias("op"), F.col("o_totalprice").alias("cost"))
    return M.amortised_ratio(runs).select("method", F.round("ratio", 6).alias("ratio"))


@BOOK.add(
    "a20_tiers",
    f"""WITH s AS (SELECT 'price' AS criterion, method, avg(n_exact) AS score FROM ({_RUNS}) GROUP BY 2 UNION ALL SELECT 'size', method, avg(recall) FROM ({_RUNS}) GROUP BY 2),
    g AS (SELECT *, ln(score) - lag(ln(score)) OVER (PARTITION BY criterion ORDER BY score, method) AS gap FROM s),
    p AS (SELECT *, row_number() OVER (PARTITION BY criterion ORDER BY gap DESC NULLS LAST, method) AS place FROM g),
    t AS (SELECT *, sum(CASE WHEN place < 4 AND gap > 0 THEN 1 ELSE 0 END) OVER (PARTITION BY criterion ORDER BY score, method) AS step FROM p)
    SELECT criterion, method, CAST(4 - max(step) OVER (PARTITION BY criterion) + step AS INTEGER) AS tier FROM t""",
)
def a20(spark, d):
    runs = _runs(spark, d).groupBy("method")
    scores = runs.agg(F.avg("n_exact").alias("score")).select(F.lit("price").alias("criterion"), "method", "score").unionByName(runs.agg(F.avg("recall").alias("score")).select(F.lit("size").alias("criterion"), "method", "score"))
    return M.tier_methods(scores).select("criterion", "method", "tier")


@BOOK.add("a21_cost_model", "SELECT vec_id, vec_id * 32 * 8 + 0.25 * 32 * vec_id * 64 AS ops FROM embeddings")
def a21(spark, d):
    return load(spark, d, "embeddings").select("vec_id", M.cost_model("vec_id", 32, 8, F.lit(0.25), 64).alias("ops"))


@BOOK.add("a22_robustness", f"SELECT method, round(regr_slope(n_exact, ln(recall)), 6) AS slope, round(corr(n_exact, ln(recall)), 6) AS corr FROM ({_RUNS}) GROUP BY 1")
def a22(spark, d):
    return M.robustness(_runs(spark, d), "recall", "n_exact").select("method", F.round("slope", 6).alias("slope"), F.round("corr", 6).alias("corr"))


_EDGES = knn_sql("SELECT vec_id, embedding FROM embeddings", "SELECT vec_id AS qid, embedding AS qvec FROM embeddings", 12, where="WHERE vec_id <> qid").replace(f"round(dist, {D})", "dist")


def knn_graph(spark, d, k=12):
    """(edges, vectors): the exact neighbour graph of the native corpus."""
    emb = C.embeddings(spark, d)
    left = emb.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
    return checkpoint(O.knn_edges(E.exact_knn(emb, left, k, plan="blocks", exclude_self=True))), emb


@BOOK.add("a17_in_degrees", f"WITH e AS ({_EDGES}) SELECT v.vec_id, count(e.vec_id) AS in_degree FROM embeddings v LEFT JOIN e ON e.vec_id = v.vec_id GROUP BY 1")
def a17(spark, d):
    edges, emb = knn_graph(spark, d)
    return M.in_degrees(edges, emb)


_WITNESS = f"""WITH e AS (SELECT qid AS src, vec_id AS dst, dist AS edge_len FROM ({_EDGES})),
  p AS (SELECT dst AS hub, src AS target, edge_len AS dist FROM e),
  w AS (SELECT p.hub, p.target, e.dst AS witness, p.dist FROM p JOIN e ON e.src = p.hub WHERE e.dst <> p.target AND round(e.edge_len, 9) <= round(p.dist, 9)),
  x AS (SELECT hub, target, witness FROM w JOIN embeddings a ON a.vec_id = witness JOIN embeddings b ON b.vec_id = target WHERE round({l2('a.embedding', 'b.embedding')}, 9) <= round(w.dist, 9))"""


@BOOK.add("m16_occlude_incoming", _WITNESS + " SELECT hub, target FROM p WHERE NOT EXISTS (SELECT 1 FROM x WHERE x.hub = p.hub AND x.target = p.target)")
def m16(spark, d):
    edges, emb = knn_graph(spark, d)
    return O.occlude_incoming(O.candidate_pairs(edges), edges, emb).select(F.col("pivot").alias("hub"), "target")


@BOOK.add("m19_witnesses", _WITNESS + " SELECT hub, target, witness FROM x")
def m19(spark, d):
    edges, emb = knn_graph(spark, d)
    return O.witnesses(O.candidate_pairs(edges), edges, emb).withColumnRenamed("pivot", "hub")


@BOOK.add(
    "m17_occlude_outgoing",
    f"""WITH RECURSIVE e AS (SELECT qid AS target, vec_id, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, vec_id) AS place FROM ({_EDGES})),
    g AS (SELECT target, 0 AS place, CAST([] AS BIGINT[]) AS kept FROM (SELECT DISTINCT target FROM e)
      UNION ALL SELECT g.target, e.place, CASE WHEN len(g.kept) < 8 AND NOT EXISTS (
        SELECT 1 FROM embeddings a, embeddings b WHERE list_contains(g.kept, a.vec_id) AND b.vec_id = e.vec_id AND round({l2('a.embedding', 'b.embedding')}, 9) <= round(e.dist, 9))
        THEN list_append(g.kept, e.vec_id) ELSE g.kept END FROM g JOIN e ON e.target = g.target AND e.place = g.place + 1)
    SELECT target, unnest(kept) AS vec_id FROM g WHERE place = 12""",
)
def m17(spark, d):
    edges, emb = knn_graph(spark, d)
    cands = edges.select(F.col("src").alias("target"), F.col("dst").alias("vec_id"), F.col("edge_len").alias("dist"))
    return O.occlude_outgoing(cands, emb, 8).select("target", "vec_id")


@BOOK.add("m18_occlude_ratio", _WITNESS.replace("round(e.edge_len, 9)", "round(1.2 * e.edge_len, 9)").replace(f"round({l2('a.embedding', 'b.embedding')}, 9)", f"round(1.2 * {l2('a.embedding', 'b.embedding')}, 9)") + " SELECT hub, target FROM p WHERE NOT EXISTS (SELECT 1 FROM x WHERE x.hub = p.hub AND x.target = p.target)")
def m18(spark, d):
    edges, emb = knn_graph(spark, d)
    return O.occlude_incoming(O.candidate_pairs(edges), edges, emb, 1.2).select(F.col("pivot").alias("hub"), "target")


@BOOK.add(
    "m22_collect_pending",
    f"WITH e AS ({_EDGES}) SELECT hub, target FROM (SELECT vec_id AS hub, qid AS target, row_number() OVER (PARTITION BY qid ORDER BY round(dist - 1.2, 9), vec_id) AS place FROM e WHERE dist - 1.2 < 0) WHERE place <= 4",
)
def m22(spark, d):
    edges, _ = knn_graph(spark, d)
    survivors = edges.select(F.col("dst").alias("pivot"), F.col("src").alias("target"), F.round(F.col("edge_len") - 1.2, 9).alias("stat")).where("edge_len - 1.2 < 0")
    return O.collect_pending(survivors, 4).select(F.col("pivot").alias("hub"), "target")


# --- companions ---------------------------------------------------------------------

_PARTS = C.hash_vectors_sql(C.PART_TOKENS_SQL, 64)


@BOOK.add(
    "r01_similar_parts_sales",
    f"""WITH v AS ({_PARTS}), n AS ({knn_sql('SELECT * FROM v', 'SELECT vec_id AS qid, embedding AS qvec FROM v WHERE vec_id % 100 = 0', 5, f"round({l2('embedding', 'qvec')}, 6)")})
    SELECT qid, count(*) AS lines, round(sum(l_extendedprice), 2) AS sales FROM n JOIN lineitem ON l_partkey = vec_id GROUP BY qid""",
)
def r01(spark, d):
    """Sales of the parts most like each queried part."""
    v = checkpoint(C.part_vec(spark, d, 64))
    pairs = E.pairs(v, C.native_queries(v), 64)
    near = E.top_k(pairs.select("qid", "vec_id", F.round(V.l2("embedding", "qvec"), 6).alias("dist")), 5)
    j = near.join(load(spark, d, "lineitem"), F.col("vec_id") == F.col("l_partkey"))
    return j.groupBy("qid").agg(F.count("*").alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("sales"))


@BOOK.add(
    "r05_label_vote",
    f"""WITH n AS ({knn_sql('SELECT vec_id, embedding FROM embeddings', 'SELECT vec_id AS qid, embedding AS qvec FROM embeddings', 5, where='WHERE vec_id <> qid')}),
    v AS (SELECT qid, e.label, count(*) AS votes FROM n JOIN embeddings e ON e.vec_id = n.vec_id GROUP BY 1, 2),
    b AS (SELECT qid, label, row_number() OVER (PARTITION BY qid ORDER BY votes DESC, label) AS p FROM v)
    SELECT count(*) AS n, CAST(sum(CAST(b.label = e.label AS INTEGER)) AS BIGINT) AS hits FROM b JOIN embeddings e ON e.vec_id = b.qid WHERE p = 1""",
)
def r05(spark, d):
    """Leave-one-out vote of the five nearest."""
    emb = load(spark, d, "embeddings")
    left = emb.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
    near = E.exact_knn(emb.select("vec_id", "embedding"), left, 5, plan="blocks", exclude_self=True)
    votes = near.join(emb.select("vec_id", "label"), "vec_id").groupBy("qid", "label").agg(F.count("*").alias("votes"))
    best = votes.withColumn("p", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("votes"), "label"))).where("p = 1")
    own = emb.select(F.col("vec_id").alias("qid"), F.col("label").alias("own"))
    return best.join(own, "qid").agg(F.count("*").alias("n"), F.sum((F.col("label") == F.col("own")).cast("int")).alias("hits"))


@BOOK.add(
    "r06_user_anomaly",
    f"""WITH v AS ({C.USER_VEC_SQL}), n AS ({knn_sql('SELECT * FROM v', 'SELECT vec_id AS qid, embedding AS qvec FROM v', 10, where='WHERE vec_id <> qid')})
    SELECT qid AS user_id, dist AS score FROM n WHERE rank = 10""",
)
def r06(spark, d):
    """Each user's distance to the tenth nearest user."""
    v = checkpoint(C.user_vec(spark, d))
    left = v.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
    return E.exact_knn(v, left, 10, plan="blocks", exclude_self=True).where("rank = 10").select(F.col("qid").alias("user_id"), F.round("dist", D).alias("score"))
