"""The experiments on the given tables: corpora, sweeps, streams, ablation, tiers, applications.

Searches within a corpus take every id divisible by 100 as queries, against all
rows; corpora with a query source of their own take all of it. Every experiment
on several sets or methods runs once for each application and folder; the queries
that report on it share its tables.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..operators import exact as E
from ..operators import measures as M
from ..operators import baselines as B
from ..operators.index import build_index, insert_batch
from ..params import Params
from ..plans import experiments as X
from ..plans import lockstep
from ..sources import corpora as C
from ..sources.session import checkpoint, materialise
from ..sources.tables import load
from ..streaming import insertion as S
from .base import Book
from .vectors import knn_sql, native

BOOK = Book()


def as_queries(df: DataFrame) -> DataFrame:
    return df.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))


def hundredth(df: DataFrame) -> DataFrame:
    return as_queries(df.where("vec_id % 100 = 0"))


def tenth(df: DataFrame) -> DataFrame:
    return as_queries(df.where("vec_id % 10 = 0"))


@dataclass(frozen=True)
class Set:
    """A corpus of a published dimension and its queries; what stands for what is in FIXTURES.md."""

    dim: int
    metric: str
    corpus: Callable[[SparkSession, str, int], DataFrame]
    #: queries of another source, or which of the corpus's own vectors are asked; those never count as their own answers
    asked: Callable[[SparkSession, str, int], DataFrame] | None = None
    own: Callable[[DataFrame], DataFrame] = hundredth
    #: shards asked for, so that large corpora are built by many tasks
    shards: int = 1

    def data(self, spark, d) -> tuple[DataFrame, DataFrame]:
        """(corpus, queries), materialised."""
        corpus = materialise(self.corpus(spark, d, self.dim), "corpus")
        return corpus, materialise(as_queries(self.asked(spark, d, self.dim)) if self.asked else self.own(corpus), "queries")

    def curve(self, spark, d, methods, k, efs) -> tuple[DataFrame, DataFrame]:
        corpus, queries = self.data(spark, d)
        return X.curve(spark, corpus, queries, methods, k, efs, self.metric, self.shards, exclude_self=self.asked is None, stored=True)


SETS = {
    "text1536": Set(1536, "l2", C.doc_vec, C.bench_vec),
    "text3072": Set(3072, "l2", C.doc_vec, C.bench_vec),
    "page512": Set(512, "l2", C.page_vec),
    "ood1536": Set(1536, "l2", C.page_vec, lambda s, d, n: C.conv_vec(s, d, n, "user")),
    "line384": Set(384, "l2", C.doc_line_vec),
    "big1024": Set(1024, "l2", C.line_vec, own=tenth, shards=8),
    "word300": Set(300, "l2", C.word_vec),
    "page960": Set(960, "l2", C.page_vec),
    "word200": Set(200, "l2", C.word_vec),
    "part150": Set(150, "l2", C.part_vec),
    "line128_cos": Set(128, "cosine", C.line_vec, shards=8),
    "line96_cos": Set(96, "cosine", C.line_vec, shards=8),
    "native64": Set(64, "l2", lambda s, d, n: C.embeddings(s, d)),
}
#: The sets of the main comparison.
MAIN = ["text1536", "text3072", "page512", "ood1536", "line384", "big1024", "word200", "line96_cos", "native64"]
#: The same vectors by Euclidean distance, for sweeps over the number of neighbours and for insertions.
LINE96 = Set(96, "l2", C.line_vec, shards=8)

_SHARED: dict[tuple, object] = {}


def once(name: str, make: Callable[[SparkSession, str], object]) -> Callable[[SparkSession, str], object]:
    """What several queries report on is run once for each application and folder."""

    def get(spark, d):
        key = (spark.sparkContext.applicationId, d, name)
        if key not in _SHARED:
            _SHARED[key] = make(spark, d)
        return _SHARED[key]

    return get


def _gated(dim: int, metric: str) -> list[X.Method]:
    return [X.Method("throughput", "graph", Params.throughput(dim, metric=metric)), X.Method("hnsw", "graph", B.hnsw_params(dim, metric=metric, m_links=32, ef_build=128))]


def _workload(name: str):
    def query(spark, d):
        """The gated graph and the layered one at three widths, K = 10."""
        own = SETS[name]
        return own.curve(spark, d, _gated(own.dim, own.metric), 10, [16, 64, 128])[0]

    return query


for _name in SETS:
    BOOK.add(f"wl_{_name}")(_workload(_name))


def _main_runs(spark, d):
    """(runs, builds) of all methods on all main sets, K = 100."""
    def one(name):
        own = replace(SETS[name], own=hundredth)
        return [df.withColumn("dataset", F.lit(name)) for df in own.curve(spark, d, X.all_methods(own.dim, own.metric), 100, [100, 200])]

    out = X.together(spark, [lambda name=name: one(name) for name in MAIN])
    return tuple(checkpoint(reduce(DataFrame.unionByName, [o[i] for o in out])) for i in (0, 1))


main_runs = once("main", _main_runs)


def _main_builds(spark, d):
    """All methods built on all main sets, without their searches; those of the main runs if these are there already."""
    if (shared := (spark.sparkContext.applicationId, d, "main")) in _SHARED:
        return _SHARED[shared][1]

    def one(name):
        own = SETS[name]
        return X.builds(own.corpus(spark, d, own.dim), X.all_methods(own.dim, own.metric), own.shards).withColumn("dataset", F.lit(name))

    return checkpoint(reduce(DataFrame.unionByName, X.together(spark, [lambda name=name: one(name) for name in MAIN])))


main_builds = once("main builds", _main_builds)


@BOOK.add("d1_curve")
def d1(spark, d):
    """Throughput and recall of all methods on all main sets, K = 100."""
    return main_runs(spark, d)[0].withColumn("nines", F.when(F.col("recall") < 1, -F.log10(1 - F.col("recall"))))


@BOOK.add("d1_pareto")
def d1b(spark, d):
    """The runs that no cheaper run of the same method beats, and speed-up over the layered graph at equal recall."""
    own = SETS["native64"]
    runs = checkpoint(own.curve(spark, d, X.all_methods(own.dim, own.metric), 10, [16, 32, 64, 128, 256])[0])
    return M.tradeoff_curve(runs).join(M.speedup_at(runs, 0.95, "hnsw"), "method", "left")


@BOOK.add("d2_build")
def d2(spark, d):
    """Build cost of all methods on all main sets: exact distances and seconds, and their ratio to the layered graph."""
    builds = main_builds(spark, d)
    base = builds.where("method = 'hnsw'").select("dataset", F.col("build_exact").alias("base_exact"), F.col("build_s").alias("base_s"))
    return builds.join(F.broadcast(base), "dataset").select(  # a row a dataset
        "dataset", "method", "n", "build_exact", "build_search", "build_s", (F.col("build_exact") / F.col("base_exact")).alias("exact_ratio"), (F.col("build_s") / F.col("base_s")).alias("time_ratio")
    )


@BOOK.add("d3_memory")
def d3(spark, d):
    """Bytes by part, and measured peaks of the build's and the search's memory (the largest shard's); codes-only methods keep vectors for reranking."""
    builds = main_runs(spark, d)[1]
    total = F.col("vectors_b") + F.col("edges_b") + F.col("projection_b") + F.col("codes_b")
    return builds.select("dataset", "method", "vectors_b", "edges_b", "projection_b", "codes_b", total.alias("total_b"), "build_peak", "search_peak")


DIMS = (384, 512, 1024, 1536, 3072)


def _dim_runs(spark, d):
    def one(dim):
        corpus, queries = C.doc_vec(spark, d, dim), as_queries(C.bench_vec(spark, d, dim))
        extra = [X.Method("qgraph", "qgraph", Params(dim), inserts=False), X.Method("qgraph_u16", "qgraph", Params(dim), (("accumulator", "u16"),), inserts=False)]
        methods = [*[m for m in X.all_methods(dim) if m.name != "qgraph"], *extra]
        return X.curve(spark, corpus, queries, methods, 10, [64])[0].withColumn("dim", F.lit(dim))

    # the highest dimensions take the longest and begin
    return checkpoint(reduce(DataFrame.unionByName, X.together(spark, [lambda dim=dim: one(dim) for dim in reversed(DIMS)])))


dim_runs = once("dims", _dim_runs)


@BOOK.add("d4_dims")
def d4(spark, d):
    """One corpus of texts over five dimensions: recall, exact distances and queries a second against the layered graph's."""
    runs = dim_runs(spark, d)
    base = runs.where("method = 'hnsw'").select("dim", F.col("n_exact").alias("base"), F.col("qps").alias("base_qps"))
    both = runs.join(F.broadcast(base), "dim")  # a row a dimension
    return both.withColumn("saving", F.col("base") / F.col("n_exact")).withColumn("qps_ratio", F.col("qps") / F.col("base_qps"))


@BOOK.add("d4_robustness")
def d4b(spark, d):
    """How the saving and the ratio of queries a second move with the dimension: slope and correlation over its logarithm."""
    runs = d4(spark, d)
    return M.robustness(runs, "dim", "saving").withColumn("of", F.lit("saving")).unionByName(M.robustness(runs, "dim", "qps_ratio").withColumn("of", F.lit("qps_ratio")))


SIZES = (10, 100, 200, 400, 600, 800, 1000)


def _size_runs(spark, d):
    methods = [*_gated(96, "l2"), X.Method("qgraph", "qgraph", Params(96), inserts=False)]
    return checkpoint(LINE96.curve(spark, d, methods, 10, [(k, max(64, k)) for k in SIZES])[0])


size_runs = once("sizes", _size_runs)


def _with_ratio(runs: DataFrame) -> DataFrame:
    base = runs.where("method = 'qgraph'").select("k", F.col("qps").alias("base"), F.col("recall").alias("base_recall"))
    both = runs.join(F.broadcast(base), "k")  # a row a size
    return both.withColumn("qps_ratio", F.col("qps") / F.col("base")).withColumn("recall_gap", F.col("recall") - F.col("base_recall"))


for _k in (10, 100, 1000):
    BOOK.add(f"d5_k{_k}")(lambda spark, d, k=_k: _with_ratio(size_runs(spark, d).where(F.col("k") == k)))


@BOOK.add("d5_sweep")
def d5(spark, d):
    """From 200 to 800 neighbours."""
    return _with_ratio(size_runs(spark, d).where("k BETWEEN 200 AND 800"))


@BOOK.add("d5_robustness")
def d5b(spark, d):
    """How queries a second and recall against the quantised graph move with the number of neighbours."""
    runs = _with_ratio(size_runs(spark, d))
    return M.robustness(runs, "k", "qps_ratio").withColumn("of", F.lit("qps_ratio")).unionByName(M.robustness(runs, "k", "recall_gap").withColumn("of", F.lit("recall_gap")))


#: Batches of insertions, and as many of searches between them.
BATCHES = 10


def _mixed(spark, d, own: Set, params: Params, k: int = 100, share: int = 6) -> DataFrame:
    """A sixth of the corpus is inserted and a sixth searched, in interleaved batches, insertions first, at equal width: a row for each batch.

    Seconds are those of the tasks that insert or search; recall is against the
    exact answers on what is there by then.
    """
    corpus = materialise(own.corpus(spark, d, own.dim), "corpus")
    initial, requests = S.mixed_requests(corpus, share, BATCHES)
    requests = materialise(requests, "requests")
    index = build_index(initial, params, shards=own.shards)
    out, paid = [], []
    for b in range(BATCHES):
        rows = requests.where(F.col("batch") == 2 * b)
        stats: list = []
        index = insert_batch(index, rows.select("vec_id", F.col("vec").alias("embedding")), stats=stats)
        n = sum(s[1] for s in stats)
        paid.append((2 * b, "insert", n, sum(s[2] for s in stats) / max(1, n), float(sum(s[3] for s in stats)) / max(1, n), len(stats)))
        asked = materialise(requests.where(F.col("batch") == 2 * b + 1).select(F.col("req_id").alias("qid"), F.col("vec").alias("qvec")), "asked")
        hits = materialise(index.search(asked, k, params.ef_build, timed=True), "hits")
        there = corpus.join(requests.where((F.col("op") == "insert") & (F.col("batch") > 2 * b)).select("vec_id"), "vec_id", "left_anti")
        truth = E.exact_knn(there, asked, k, own.metric, plan="blocks")
        recall = M.recall_at_k(hits, truth, k)
        one = hits.where("rank = 1").agg(F.count("*").alias("n"), F.avg("search_s").alias("seconds"), F.avg("n_exact").alias("n_exact"))
        out.append(recall.crossJoin(F.broadcast(one)).select(F.lit(2 * b + 1).alias("batch"), F.lit("search").alias("op"), "n", "seconds", "n_exact", F.lit(index.shards).alias("shards"), "recall"))  # one row each
    inserts = spark.createDataFrame(paid, "batch int, op string, n bigint, seconds double, n_exact double, shards int").withColumn("recall", F.lit(None).cast("double"))
    searches = reduce(DataFrame.unionByName, out)
    return checkpoint(inserts.unionByName(searches).withColumn("method", F.lit(params.preset)))


def _insertion_params(dim: int) -> list[Params]:
    return [Params.throughput(dim), Params.compact(dim, ef_build=128), B.hnsw_params(dim, m_links=32, ef_build=128)]


mixed_runs = {p.preset: once(f"mixed {p.preset}", lambda spark, d, p=p: _mixed(spark, d, LINE96, p)) for p in _insertion_params(96)}


@BOOK.add("d6_stream")
def d6(spark, d):
    """Twenty interleaved batches of insertions and searches, K = 100: what each costs and finds."""
    return mixed_runs["throughput"](spark, d)


@BOOK.add("d6_compare")
def d6b(spark, d):
    """The mixed stream by both presets and the layered graph."""
    return reduce(DataFrame.unionByName, [get(spark, d) for get in mixed_runs.values()])


@BOOK.add("d6_insert_cost")
def d6c(spark, d):
    """Cost of an insertion over that of a search at equal width, in exact distances and seconds, and how it moves over the batches: the amortised condition."""
    runs = d6b(spark, d)
    out = M.amortised_ratio(runs.select("method", "op", F.col("n_exact").alias("cost"))).withColumnRenamed("ratio", "exact_ratio")
    out = out.join(M.amortised_ratio(runs.select("method", "op", F.col("seconds").alias("cost"))).withColumnRenamed("ratio", "time_ratio"), "method")
    moves = runs.where("op = 'insert'").groupBy("method").agg(F.corr("batch", "n_exact").alias("trend"), (F.max("n_exact") / F.min("n_exact")).alias("spread"))
    return out.join(moves, "method")


@BOOK.add("d6_ood_corpus")
def d6d(spark, d):
    """The mixed stream on the corpus of the out-of-distribution set, queries from the corpus itself."""
    own = Set(1536, "l2", C.page_vec)
    return reduce(DataFrame.unionByName, [_mixed(spark, d, own, p, k=20) for p in (Params.throughput(1536), B.hnsw_params(1536, m_links=32, ef_build=128))])


@BOOK.add("ablation")
def ablation(spark, d):
    """The gate alone, with rings, with rings and screen, on four sets; with the build's cost."""
    def one(name):
        own = SETS[name]
        runs, builds = own.curve(spark, d, X.ablation_methods(own.dim, own.metric), 10, [64, 128])
        return runs.join(builds.select("method", "build_exact", "build_search", "build_s", "edges", "screen_edges", "zero_in", "build_peak"), "method").withColumn("dataset", F.lit(name))

    return reduce(DataFrame.unionByName, X.together(spark, [lambda name=name: one(name) for name in ("text3072", "page512", "line384", "ood1536")]))


@BOOK.add("tiers")
def tiers(spark, d):
    """Methods by the six criteria: tiers of cost at equal recall, build cost and bytes, and whether recall holds at high dimensions, at many neighbours, and vectors can be added."""
    runs, builds = main_runs(spark, d)
    name = "text1536"
    runs, builds = runs.where(F.col("dataset") == name), builds.where(F.col("dataset") == name)
    search = M.cost_at(runs, 0.8, "seconds") if "seconds" in runs.columns else M.cost_at(runs.withColumn("seconds", 1 / F.col("qps")), 0.8, "seconds")
    total = F.col("vectors_b") * F.col("method").isin("ivfpq", "aniso", "scalar").cast("int") * -1 + F.col("vectors_b") + F.col("edges_b") + F.col("projection_b") + F.col("codes_b")
    scores = [
        search.select(F.lit("search").alias("criterion"), "method", (1 / F.col("cost")).alias("score")),
        builds.select(F.lit("build").alias("criterion"), "method", (1 / F.col("build_s")).alias("score")),
        builds.select(F.lit("memory").alias("criterion"), "method", (1 / total).alias("score")),
    ]
    tiered = M.tier_methods(reduce(DataFrame.unionByName, scores)).withColumn("holds", F.lit(None).cast("boolean"))
    dims = dim_runs(spark, d).groupBy(F.when(F.col("method") == "qgraph_u16", "qgraph").otherwise(F.col("method")).alias("method")).agg(F.min("recall").alias("least"), F.max("recall").alias("most"))
    high = dims.select(F.lit("dimension").alias("criterion"), "method", F.col("least").alias("score"), F.lit(None).cast("int").alias("tier"), (F.col("least") >= 0.5 * F.col("most")).alias("holds"))
    many = size_runs(spark, d).where("k = 1000").select(F.lit("neighbours").alias("criterion"), "method", F.col("recall").alias("score"), F.lit(None).cast("int").alias("tier"), (F.col("recall") >= 0.9).alias("holds"))
    added = spark.createDataFrame([("insertion", m.name, 0.0, None, m.inserts) for m in X.all_methods(96)], "criterion string, method string, score double, tier int, holds boolean")
    return reduce(DataFrame.unionByName, [tiered, high, many, added])


@BOOK.add("bsp_search")
def bsp(spark, d):
    """The lock-step search over one global graph, by joins."""
    emb, q = native(spark, d)
    index = build_index(emb, Params(64, work=8, m_links=8, ef_build=32))
    return lockstep.search(index, q, 5, 8).withColumn("dist", F.round("dist", 5))


# --- applications -------------------------------------------------------------------


@BOOK.add("app_rag")
def rag(spark, d):
    """For each user turn the ten documents nearest to it."""
    docs, asked = C.doc_vec(spark, d, 384), as_queries(C.conv_vec(spark, d, 384, "user"))
    index = build_index(materialise(docs, "corpus"), Params.throughput(384, ef_build=64), shards=8)
    return index.search(asked, 10, 64).select("qid", "rank", "vec_id", F.round("dist", 5).alias("dist"))


@BOOK.add("app_pages")
def pages(spark, d):
    """Two hundred pages for each queried page."""
    corpus = materialise(C.page_vec(spark, d, 512), "corpus")
    return build_index(corpus, Params.throughput(512, ef_build=64)).search(hundredth(corpus), 200, 200).select("qid", "rank", "vec_id", F.round("dist", 5).alias("dist"))


@BOOK.add("app_recsys")
def recsys(spark, d):
    """Up to a hundred users like each queried user, by when they do what."""
    users = materialise(C.user_vec(spark, d), "corpus")
    return build_index(users, Params(120)).search(hundredth(users), 100, 128).select("qid", "rank", "vec_id", F.round("dist", 5).alias("dist"))


@BOOK.add("app_memory")
def memory(spark, d):
    """An agent's memory: turns come one after the other; each search sees only earlier turns."""
    turns = materialise(C.conv_vec(spark, d, 384).join(C.turn_ids(spark, d).select("vec_id", F.col("turn").cast("int").alias("turn")), "vec_id"), "corpus")
    times = sorted(r.turn for r in turns.select("turn").distinct().collect())  # a row a turn
    out = [spark.createDataFrame([], "qid bigint, rank int, vec_id bigint, dist double, turn int")]
    index = build_index(turns.where(F.col("turn") == times[0]), Params(384, ef_build=64)) if times else None
    for t in times[1:]:
        now = turns.where(F.col("turn") == t)
        out.append(index.search(as_queries(now), 5, 32).select("qid", "rank", "vec_id", "dist", F.lit(t).alias("turn")))
        if t != times[-1]:  # nothing is searched after the last turn
            index = insert_batch(index, now)
    return reduce(DataFrame.unionByName, out).select("turn", "qid", "rank", "vec_id", F.round("dist", 5).alias("dist"))


@BOOK.add("r02_similar_customers")
def r02(spark, d):
    """Regions of the customers most like each queried customer."""
    corpus = materialise(C.customer_vec(spark, d, 96), "corpus")
    hits = build_index(corpus, Params(96)).search(hundredth(corpus), 10, 64)
    who = load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    return hits.join(who, F.col("vec_id") == F.col("c_custkey")).rollup("r_name", "n_name").agg(F.count("*").alias("hits"), F.round(F.avg("c_acctbal"), 2).alias("balance"))


@BOOK.add("r03_near_copy_votes")
def r03(spark, d):
    """Groups of documents within a radius of each other, by searches of the graph and connected links; votes of the labels inside each group.

    Copies share a node, which asks and answers for them, so that they take no
    place among the twelve from different vectors; they vote in its group.
    """
    corpus = materialise(C.doc_vec(spark, d, 384), "corpus")
    labels = load(spark, d, "labels")
    index = build_index(corpus, Params(384, ef_build=64), shards=4)
    members = checkpoint(index.members())
    asked = corpus.join(members.where("vec_id != rep_id"), "vec_id", "left_anti")
    near = index.search(as_queries(asked), 12, 48, within=0.6, with_copies=False).where("vec_id != qid").select("qid", "vec_id")
    # one document's links are few, so the least reachable id is found by passing ids along until none falls
    links = checkpoint(near.union(near.select("vec_id", "qid")).distinct())
    state = checkpoint(members.where("vec_id = rep_id").select("vec_id", F.col("vec_id").alias("grp")))
    while True:
        met = links.join(state.select(F.col("vec_id").alias("qid"), F.col("grp").alias("other")), "qid").groupBy("vec_id").agg(F.min("other").alias("other"))
        after = checkpoint(state.join(met, "vec_id", "left").select("vec_id", F.least("grp", F.coalesce("other", "grp")).alias("grp"), F.col("grp").alias("was")))
        if after.where("grp != was").isEmpty():
            break
        state = after.select("vec_id", "grp")
    named = members.join(state.select(F.col("vec_id").alias("rep_id"), "grp"), "rep_id")
    votes = named.join(labels.select(F.col("doc_id").alias("vec_id"), "quality"), "vec_id").groupBy("grp").agg(F.count("*").alias("members"), F.avg("quality").alias("share"))
    return votes.groupBy("members").agg(F.count("*").alias("groups"), F.avg(F.greatest("share", 1 - F.col("share"))).alias("agreement"))


@BOOK.add("r04_nearest_items")
def r04(spark, d):
    """For each benchmark item the lines of documents nearest to it, and the documents' sources."""
    lines = materialise(C.doc_line_vec(spark, d, 384), "corpus")
    hits = build_index(lines, Params(384, ef_build=48, m_links=12), shards=8).search(as_queries(C.bench_vec(spark, d, 384)), 3, 48)
    named = hits.join(C.line_ids(spark, d).select("vec_id", "doc_id"), "vec_id")
    return named.join(load(spark, d, "documents").select("doc_id", "source"), "doc_id").select("qid", "rank", "doc_id", "source", F.round("dist", 5).alias("dist"))


# --- sources, sinks and surface -----------------------------------------------------


@BOOK.add("s02_format_round_trips", "SELECT 'csv' AS kind, count(*) AS n, CAST(sum(n_nationkey) AS BIGINT) AS keys FROM nation UNION ALL SELECT 'json', count(*), CAST(sum(n_nationkey) AS BIGINT) FROM nation UNION ALL SELECT 'orc', count(*), CAST(sum(n_nationkey) AS BIGINT) FROM nation UNION ALL SELECT 'text', count(*), CAST(sum(length(n_name)) AS BIGINT) FROM nation")
def s02(spark, d):
    from ..sources.formats import read_as, write_as
    from ..sources.session import shared_folder

    nation, out = load(spark, d, "nation"), []
    for kind in ("csv", "json", "orc"):
        path = shared_folder(spark, kind)
        write_as(nation, kind, path)
        out.append(read_as(spark, kind, path, nation.schema).agg(F.lit(kind).alias("kind"), F.count("*").alias("n"), F.sum("n_nationkey").alias("keys")))
    path = shared_folder(spark, "text")
    nation.select(F.col("n_name").alias("value")).write.text(path)
    out.append(spark.read.text(path).agg(F.lit("text").alias("kind"), F.count("*").alias("n"), F.sum(F.length("value")).alias("keys")))
    return reduce(DataFrame.unionByName, out)


@BOOK.add("s03_packed_vectors", "SELECT vec_id, true AS same FROM embeddings")
def s03(spark, d):
    from ..sources.formats import pack, unpack

    emb = C.embeddings(spark, d)
    return emb.join(unpack(pack(emb)).withColumnRenamed("embedding", "back"), "vec_id").select("vec_id", (F.col("embedding") == F.col("back")).alias("same"))


@BOOK.add("s03_local_quantisation", "SELECT vec_id, true AS close FROM embeddings")
def s03b(spark, d):
    from ..functions import vectors as V
    from ..sources.formats import dequantise_local, quantise_local

    emb = C.embeddings(spark, d)
    back = dequantise_local(quantise_local(emb)).withColumnRenamed("embedding", "back")
    return emb.join(back, "vec_id").select("vec_id", (V.linf("embedding", "back") < 1e-4).alias("close"))


@BOOK.add("s04_vector_files", "SELECT count(*) AS n, CAST(64 AS INTEGER) AS dim FROM embeddings")
def s04(spark, d):
    from ..sources.formats import read_fvecs, write_fvecs
    from ..sources.session import shared_folder

    path = shared_folder(spark, "vectors")
    write_fvecs(C.embeddings(spark, d), path)
    return read_fvecs(spark.read.parquet(path)).agg(F.count("*").alias("n"), F.max(F.size("embedding")).alias("dim"))


@BOOK.add("s05_index_files", "SELECT count(DISTINCT embedding) AS nodes, count(*) AS vectors, CAST(0 AS BIGINT) AS pending, true AS same FROM embeddings")
def s05(spark, d):
    """An index written, opened by its path and read part by part."""
    from ..operators.index import Index

    emb, _ = native(spark, d)
    index = build_index(emb, Params(64), shards=3)
    again = Index.open(spark, index.path)
    one = again.nodes().agg(F.count("*").alias("nodes")).crossJoin(F.broadcast(again.rows.agg((F.count("*") + F.sum(F.size("copies"))).alias("vectors"))))  # one row each
    one = one.crossJoin(F.broadcast(again.pending().agg(F.count("*").alias("pending"))))
    return one.select("nodes", "vectors", "pending", F.lit(again.params == index.params and again.generations == index.generations).alias("same"))


@BOOK.add("s09_noop_sink", "SELECT count(*) AS n FROM lineitem")
def s09(spark, d):
    """A table run to its last row without a sink; the rows are counted on the way."""
    from pyspark.sql import Observation

    seen = Observation("rows")
    load(spark, d, "lineitem").observe(seen, F.count("*").alias("n")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"],)], "n bigint")


_FIRST = "SELECT vec_id, embedding FROM embeddings"


@BOOK.add("u04_search_table_function", knn_sql(_FIRST, "SELECT vec_id AS qid, embedding AS qvec FROM embeddings WHERE vec_id = 0", 10).replace("SELECT qid, CAST(rank AS INTEGER) AS rank, vec_id, round(dist, 6) AS dist", "SELECT vec_id, round(dist, 5) AS dist"))
def u04(spark, d):
    """The search as a table function in SQL, over the shards of an index, as wide as the graph."""
    from ..functions.aggregates import register_search

    emb, _ = native(spark, d)
    n = emb.count()
    register_search(spark, build_index(emb, Params(64, work=n), shards=2))
    asked = ", ".join(f"CAST({v!r} AS FLOAT)" for v in emb.where("vec_id = 0").first().embedding)
    return spark.sql(f"SELECT vec_id, round(dist, 5) AS dist FROM ann_search(TABLE(SELECT * FROM ann_search_shards) PARTITION BY (shard), array({asked}), 10, {n}) ORDER BY dist, vec_id LIMIT 10")


@BOOK.add("u04_hops_table_function")
def u04b(spark, d):
    """Neighbours of a node by edges, as a table function."""
    from pyspark.sql.functions import udtf

    emb, _ = native(spark, d)
    build_index(emb, Params(64)).edges().createOrReplaceTempView("index_edges")

    class Hops:
        def eval(self, near: list, hops: int):
            for place, node in enumerate(near or []):
                if place < hops:
                    yield node, place + 1

    spark.udtf.register("near_nodes", udtf(Hops, returnType="node bigint, place int"))
    return spark.sql("SELECT n.src, f.node, f.place FROM (SELECT src, transform(array_sort(collect_list(struct(edge_len, dst))), e -> e.dst) AS near FROM index_edges GROUP BY src) n, LATERAL near_nodes(n.near, 3) f")


@BOOK.add("u06_inspection_views", "SELECT count(DISTINCT embedding) AS nodes, true AS linked, CAST(0 AS BIGINT) AS pending, '64' AS dim FROM embeddings")
def u06(spark, d):
    """The parts of an index as views."""
    from ..functions.aggregates import register_inspection

    emb, _ = native(spark, d)
    register_inspection(spark, build_index(emb, Params(64)))
    return spark.sql(
        """SELECT (SELECT count(*) FROM index_nodes) AS nodes, (SELECT count(*) FROM index_edges) > (SELECT count(*) FROM index_nodes) AS linked,
        (SELECT count(*) FROM index_pending) AS pending, (SELECT value FROM index_manifest WHERE name = 'dim') AS dim"""
    )


@BOOK.add("g07_top_k_aggregate", "SELECT label, vec_id, CAST(place AS INTEGER) AS place FROM (SELECT label, vec_id, row_number() OVER (PARTITION BY label ORDER BY embedding[1], vec_id) AS place FROM embeddings) WHERE place <= 5")
def g07(spark, d):
    """The five vectors of each label with the least first element, by an aggregate."""
    from ..functions.aggregates import top_k_by

    best = load(spark, d, "embeddings").groupBy("label").agg(top_k_by(5)(F.get("embedding", 0).cast("double"), F.col("vec_id")).alias("best"))
    return best.select("label", F.posexplode("best").alias("place", "vec_id")).select("label", "vec_id", (F.col("place") + 1).alias("place"))


_MEANS = "SELECT label, CAST(i - 1 AS INTEGER) AS pos, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS mean FROM embeddings, (SELECT unnest(range(1, 65)) AS i) GROUP BY 1, 2"


@BOOK.add("u03_vector_average", _MEANS)
def u03(spark, d):
    """Mean vectors by an aggregate function."""
    from ..functions.aggregates import vec_avg

    means = load(spark, d, "embeddings").groupBy("label").agg(vec_avg("embedding").alias("mean"))
    return means.select("label", F.posexplode("mean").alias("pos", "mean")).select("label", "pos", F.round("mean", 6).alias("mean"))


@BOOK.add("g08_partial_vector_sums", _MEANS)
def g08b(spark, d):
    """Mean vectors by partial sums of each task."""
    from ..functions.aggregates import vector_mean

    means = vector_mean(load(spark, d, "embeddings"), "label")
    return means.select("label", F.posexplode("mean").alias("pos", "mean")).select("label", "pos", F.round("mean", 6).alias("mean"))


@BOOK.add("u02_arrow_function", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * v))), 6) AS norm FROM embeddings")
def u02(spark, d):
    from ..functions.aggregates import arrow_norm

    return load(spark, d, "embeddings").select("vec_id", F.round(arrow_norm("embedding"), 6).alias("norm"))


@BOOK.add("j03_bucketed_join", "SELECT l_returnflag, o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")
def j03(spark, d):
    """Two tables bucketed by the joined key: they meet without an exchange."""
    lines, orders = bucketed(load(spark, d, "lineitem"), "l_orderkey"), bucketed(load(spark, d, "orders"), "o_orderkey")
    both = lines.hint("merge").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return both.groupBy("l_returnflag", "o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


def bucketed(df: DataFrame, key: str, buckets: int = 8) -> DataFrame:
    """The rows as a table bucketed and sorted by a key, in the shared folder."""
    import uuid

    from ..sources.session import shared_folder

    name = f"bucketed_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, key).sortBy(key).option("path", shared_folder(df.sparkSession, name)).saveAsTable(name)
    return df.sparkSession.table(name)


@BOOK.add("t06_window_rates", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1, 2")
def t06(spark, d):
    """Request rates by hour and kind; the streaming form is in ``streaming.windows``."""
    w = F.window(F.col("ts"), "1 hour")
    return load(spark, d, "events").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n", "mean")


@BOOK.add(
    "t06_sessions",
    """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
    s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""",
)
def t06b(spark, d):
    s = F.session_window(F.col("ts"), "30 minutes")
    return load(spark, d, "events").groupBy(s.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@BOOK.add("n04_top_events", "SELECT event_type, event_id, place FROM (SELECT event_type, event_id, CAST(row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS INTEGER) AS place FROM events) WHERE place <= 10")
def n04b(spark, d):
    w = Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id")
    return load(spark, d, "events").withColumn("place", F.row_number().over(w)).where("place <= 10").select("event_type", "event_id", "place")
