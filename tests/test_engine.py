"""The Spark side: index, shards, lock-step search, experiments, files, streams, worked examples."""

import threading
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecgraph.operators import baselines as B
from vecgraph.operators import exact as E
from vecgraph.operators import measures as M
from vecgraph.operators import quantised as Z
from vecgraph.operators import index as I
from vecgraph.operators.index import Index, build_index, from_parts, insert_batch, to_parts
from vecgraph.operators.kernel import Graph, build
from vecgraph.operators.projection import target_table
from vecgraph.params import Params
from vecgraph.plans import experiments as X
from vecgraph.plans import lockstep
from vecgraph.sources import corpora as C
from vecgraph.sources import formats as S


@pytest.fixture(scope="module")
def native(spark, small):
    emb = C.embeddings(spark, small).persist()
    return emb, C.native_queries(emb).persist()


def test_rows_round_trip_with_layers_and_copies():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(200, 16)).astype(np.float32)
    x[150:] = x[:50]
    for params in (Params(16), B.hnsw_params(16, m_links=4), Params(16, half=True)):
        g = build(np.arange(200), x, params)
        h = from_parts([r for b in to_parts(g, 0) for r in b.to_pylist()], params)
        assert (h.adj[: h.size] == g.adj[: g.size]).all() and h.copies == g.copies and len(h.upper) == len(g.upper)
        if not params.half:
            a, b = g.search(x[:10], 5, 32), h.search(x[:10], 5, 32)
            assert (a.ids == b.ids).all()


def test_index_recall_files_and_insertion(spark, native):
    emb, q = native
    truth = E.exact_knn(emb, q, 10).persist()
    index = build_index(emb, Params(64))
    again = Index.open(spark, index.path)
    assert again.params == index.params
    assert M.recall_at_k(again.search(q, 10, 96), truth, 10).first()[0] >= 0.9
    edges = index.edges()
    assert edges.where("src = dst").isEmpty() and edges.groupBy("src").count().agg(F.max("count")).first()[0] <= index.params.cap
    half = build_index(emb.where("vec_id % 2 = 0"), Params(64))
    full = insert_batch(half, emb.where("vec_id % 2 = 1"))
    assert full.rows.count() == emb.count() and insert_batch(full, emb).rows.count() == emb.count()
    assert M.recall_at_k(full.search(q, 10, 96), truth, 10).first()[0] >= 0.9


def test_shards_and_probes(native):
    emb, q = native
    truth = E.exact_knn(emb, q, 10).persist()
    index = build_index(emb, Params(64, shard_size=150))
    assert index.shards >= 4 and index.rows.groupBy("shard").count().agg(F.max("count")).first()[0] <= 150 * 1.5
    assert M.recall_at_k(index.search(q, 10, 64), truth, 10).first()[0] >= 0.95
    few = M.recall_at_k(index.search(q, 10, 64, probes=2), truth, 10).first()[0]
    assert 0.2 <= few <= 1


def test_copies_meet_in_one_shard(spark):
    x = np.random.default_rng(3).normal(size=(200, 16)).astype(np.float32)
    table = lambda first: spark.createDataFrame([(first + i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<float>")
    index = build_index(table(0).unionByName(table(200)), Params(16, shard_size=40))
    assert index.shards > len(set(index.cells.tolist())) and index.rows.count() == 200 == index.copies().count()
    assert insert_batch(index, table(400)).rows.count() == 200


def test_presets_move_as_documented(native):
    emb, q = native
    truth = E.exact_knn(emb, q, 10).persist()
    fast, small = build_index(emb, Params.throughput(64)), build_index(emb, Params.compact(64))
    size = lambda i: i.size_report().agg(F.sum("bytes")).first()[0]
    assert size(small) < size(fast)
    assert M.recall_at_k(fast.search(q, 10, 64), truth, 10).first()[0] >= M.recall_at_k(small.search(q, 10, 64), truth, 10).first()[0]


@pytest.mark.parametrize("gate", [False, True])
def test_lockstep_equals_kernel(native, gate):
    emb, q = native
    index = build_index(emb, Params(64, work=5, m_links=6, ef_build=24))
    ask = q.where("qid < 200")
    a = [(r.qid, r.rank, r.vec_id, r.n_exact) for r in lockstep.search(index, ask, 4, 7, gate=gate).orderBy("qid", "rank").collect()]
    b = [(r.qid, r.rank, r.vec_id, r.n_exact) for r in index.search(ask, 4, 7, gate=gate).orderBy("qid", "rank").collect()]
    assert a == b and len(a) == 8


def test_all_methods_reach_recall(spark, native):
    emb, q = native
    runs = {r.method: r for r in X.curve(spark, emb, q, X.all_methods(64) + X.ablation_methods(64), 10, [128])[0].collect()}
    for name in ("throughput", "compact", "hnsw", "hnsw_test", "vamana", "nsg", "gate_rings_screen"):
        assert runs[name].recall >= 0.9, name
    for name in ("ivfpq", "aniso", "scalar", "qgraph"):
        assert runs[name].recall >= 0.6, name
    assert runs["gate_rings"].n_exact < runs["gate"].n_exact < runs["no_gate"].n_exact


def test_curve_over_shards_searches_and_counts_all_of_them(spark, native, monkeypatch):
    """Whatever the limit of a shard, every vector is built once, every query reaches every shard, and a full width is exact."""
    emb, q = native
    n = emb.count()
    one = None
    for size in (0, n - 1, n, n + 1, 120):
        method = X.Method("none", "graph", B.no_gate_params(64, shard_size=size))
        runs, builds = (df.collect() for df in X.curve(spark, emb, q, [method], 10, [n]))
        assert len(runs) == len(builds) == 1 and builds[0].n == n and runs[0].recall == 1.0
        one = runs[0].n_exact if one is None else one
        assert runs[0].n_exact >= one - 5
    monkeypatch.setattr(X, "SENT_FLOATS", 64 * 2)  # queries in blocks of two
    again, builds = X.curve(spark, emb, q, [method], 10, [n])
    assert again.collect()[0].recall == 1.0 and builds.collect()[0].n == n
    # builds are reported without queries as well
    assert X.run(emb, q.where("qid < 0"), [method], [(10, 128)])[1].collect()[0].n == n
    with pytest.raises(ValueError):
        X.curve(spark, emb, q, [method], n + 1, [n])


@pytest.mark.parametrize("metric, own", [("l2", True), ("cosine", False)])
def test_curve_counts_answers_in_the_tasks(spark, native, metric, own, monkeypatch):
    """A row for each setting, query and shard, not for each answer; recall is that of the merged answers."""
    emb, q = native
    methods = [X.Method("few", "graph", Params(64, metric=metric, m_links=3, work=4, ef_build=8, shard_size=80)), X.Method("scalar", "scalar", Params(64, metric=metric))]
    settings = [(5, 8), (30, 30), (30, 40)]
    seen = []
    monkeypatch.setattr(X, "summary", lambda counts, limits, f=X.summary: seen.append((counts, limits)) or f(counts, limits))
    runs = X.curve(spark, emb, q, methods, 5, settings, metric, exclude_self=own)[0].collect()
    (counts, limits), m = seen[0], q.count()
    shards = X.raw_shards(emb, methods[0].params)[0].select("shard").distinct().count()
    assert shards > 1 and counts.count() == len(methods) * len(settings) * m * shards and limits.count() == 2 * m
    truth = E.exact_knn(emb, q, 30, metric, plan="blocks", exclude_self=own)
    if metric == "cosine":
        truth = truth.selectExpr("qid", "rank", "vec_id", "sqrt(2 * greatest(dist, 0D)) AS dist")
    answers = X.run(emb, q, methods, settings, exclude_self=own)[0].persist()
    for k in (5, 30):
        want = {(r.method, r.ef): r.recall for r in X.M.recall_at_k(answers.where(f"k = {k}"), truth, k, ["method", "ef"]).collect()}
        assert {(r.method, r.ef): round(r.recall, 9) for r in runs if r.k == k} == {key: round(v, 9) for key, v in want.items()}
    cost = {(r.method, r.k, r.ef): r for r in X.M.cost_report(answers, ["method", "k", "ef"]).collect()}
    for r in runs:
        assert (r.n_exact, r.n_visited, r.pass_ratio, r.queries) == (cost[r.method, r.k, r.ef].n_exact, cost[r.method, r.k, r.ef].n_visited, cost[r.method, r.k, r.ef].pass_ratio, m)
    assert any(0 < r.recall < 1 for r in runs)


def test_experiments_keep_little_in_the_driver(spark, native, monkeypatch):
    """No sample of vectors comes to the driver, queries come in small blocks, once for all methods, and a shard is built once for all blocks."""
    emb, q = native
    methods = [X.Method("few", "graph", Params(64, m_links=3, work=4, ef_build=8, shard_size=80)), X.Method("scalar", "scalar", Params(64))]
    runs = lambda: [sorted(df.drop("qps", "build_s", "build_peak", "search_peak").collect()) for df in X.curve(spark, emb, q, methods, 5, [8, 16], shards=2)]
    whole = runs()
    assert len(whole[0]) == 4 and q.count() > 4
    monkeypatch.setattr(X, "HELD_FLOATS", 66 * 4)
    monkeypatch.setattr(E, "HELD_FLOATS", 64 * 4)
    fetched, written, kind = [], [], type(emb)
    monkeypatch.setattr(kind, "toArrow", lambda df, f=kind.toArrow: fetched.append(f(df)) or fetched[-1])
    monkeypatch.setattr(X, "materialise", lambda df, name, f=X.materialise: written.append(name) or f(df, name))
    assert runs() == whole
    assert written.count("experiment") == 1
    assert sum(t.num_rows for t in fetched) == 2 * q.count() and max(t.num_rows for t in fetched) < q.count()


def test_experiments_on_several_sets_are_under_way_at_once(spark, small, monkeypatch):
    """Whole experiments over sets and dimensions overlap; every one is there, in its order."""
    from vecgraph.queries import workloads as W

    built = "build_exact build_search build_s edges screen_edges zero_in build_peak".split()
    now, most, lock = [0], [0], threading.Lock()

    def curve(*_, **__):
        with lock:
            now[0] += 1
            most[0] = max(most[0], now[0])
        time.sleep(0.5)
        with lock:
            now[0] -= 1
        return spark.createDataFrame([("hnsw",)], "method string"), spark.createDataFrame([("hnsw", *range(7))], ["method", *built])

    monkeypatch.setattr(X, "curve", curve)
    for run, name, wanted in ((lambda: W._dim_runs(spark, small), "dim", set(W.DIMS)), (lambda: W.ablation(spark, small), "dataset", {"text3072", "page512", "line384", "ood1536"}), (lambda: W._main_runs(spark, small)[1], "dataset", set(W.MAIN))):
        most[0] = 0
        got = [r[0] for r in run().select(name).collect()]
        assert set(got) == wanted and len(got) == len(wanted) and 1 < most[0] <= X.AT_ONCE
    assert X.together(spark, [lambda i=i: i for i in range(7)]) == list(range(7))


def test_builds_are_reported_without_searches(spark, native, monkeypatch):
    """What ``d2_build`` reports asks for no query and no exact answer, and is what the whole runs report."""
    from vecgraph.queries import workloads as W

    emb, q = native
    methods = [X.Method("few", "graph", Params(64, m_links=3, work=4, ef_build=8, shard_size=80)), X.Method("scalar", "scalar", Params(64))]
    told = ("method", "n", "build_exact", "build_search", "edges", "screen_edges", "vectors_b", "edges_b", "projection_b", "codes_b", "zero_in")
    whole = sorted(X.curve(spark, emb, q, methods, 5, [8])[1].select(*told).collect())
    monkeypatch.setattr(X, "curve", None)
    monkeypatch.setattr(X, "kth_distances", None)
    assert sorted(X.builds(emb, methods).select(*told).collect()) == whole
    own = W.Set(64, "l2", lambda s, d, n: emb, lambda *_: pytest.fail("queries are made"))
    monkeypatch.setattr(W, "SETS", {"one": own})
    monkeypatch.setattr(W, "MAIN", ["one"])
    monkeypatch.setattr(W, "_SHARED", {})
    monkeypatch.setattr(X, "all_methods", lambda dim, metric: [*methods, X.Method("hnsw", "graph", B.hnsw_params(64))])
    rows = {r.method: r for r in W.d2(spark, "nowhere").collect()}
    assert set(rows) == {"few", "scalar", "hnsw"} and rows["hnsw"].exact_ratio == 1 and rows["few"].n == emb.count()


def test_a_set_is_stored_once(spark, native, monkeypatch):
    """The corpus of an experiment is written as a table once, not again by the curve."""
    from vecgraph.queries import workloads as W

    emb, _ = native
    written = []
    for module in (W, X):
        monkeypatch.setattr(module, "materialise", lambda df, name, f=module.materialise: written.append(name) or f(df, name))
    own = W.Set(64, "l2", lambda s, d, n: emb)
    assert own.curve(spark, "nowhere", [X.Method("few", "graph", Params(64, m_links=3, ef_build=8))], 5, [8])[0].count() == 1
    assert written.count("corpus") == written.count("queries") == 1


def test_growing_parts_are_under_way_at_once(spark, small, monkeypatch):
    """The parts of the lines overlap, the smallest part is the first row, and none is written twice."""
    from vecgraph.queries import methods as Q

    now, most, lock = [0], [0], threading.Lock()

    def curve(_, corpus, queries, *__, stored=False, **___):
        assert stored and queries.count() <= corpus.count()
        with lock:
            now[0] += 1
            most[0] = max(most[0], now[0])
        time.sleep(2)
        with lock:
            now[0] -= 1
        return spark.createDataFrame([(0.5, 16, 1.0, 2.0), (0.95, 32, 2.0, 3.0)], "recall double, ef int, n_visited double, n_exact double"), None

    monkeypatch.setattr(X, "curve", curve)
    rows = Q.a11(spark, small).collect()
    assert [r.ef for r in rows] == [32] * 4 and 1 < most[0] <= X.AT_ONCE
    assert [r.n for r in rows] == sorted(r.n for r in rows) and rows[-1].n == C.doc_line_vec(spark, small, 96).count()


def test_kth_distances_are_those_of_exact_answers(spark, native, monkeypatch):
    emb, q = native
    truth = {(r.qid, r["rank"]): r.dist for r in E.exact_knn(emb, q, 12, plan="blocks", exclude_self=True).collect()}
    for gathered in (1, 64 << 20):
        monkeypatch.setattr(E, "GATHERED_BYTES", gathered)
        got = E.kth_distances(emb.repartition(3), q, [12, 1, 5], exclude_self=True).collect()
        assert len(got) == 3 * q.count() and all(r.want == r.k and abs(r.limit - truth[r.qid, r.k]) < 1e-12 for r in got)
    few = E.kth_distances(emb.where("vec_id < 4"), q.where("qid = 0"), [2, 9]).collect()
    assert sorted((r.k, r.want) for r in few) == [(2, 2), (9, 4)] and E.kth_distances(emb, q.limit(0), [3]).count() == 0


def test_search_moves_no_index_and_insertion_writes_one_shard(spark, native):
    emb, q = native
    index = build_index(emb.where("vec_id != 7"), Params(64), shards=4)
    assert index.shards >= 4
    plan = index.search(q, 10, 64)._jdf.queryExecution().executedPlan().toString()
    scan = plan[plan.index("MapInArrow") :]
    assert "Exchange" not in scan and plan.count("Exchange") == 1  # only answers are exchanged
    few = index.search(q.where("qid = 0"), 10, 64, probes=1)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(shard" in few or "PartitionFilters: [(shard" in few or "shard#" in few.split("PartitionFilters")[1][:80]
    more = insert_batch(index, emb.where("vec_id = 7"))
    assert [len(held) for _, held in more.generations[1:]] == [1] and more.generations[0] == index.generations[0]
    assert more.rows.count() == emb.count() and index.rows.count() == emb.count() - 1
    hit = more.search(emb.where("vec_id = 7").selectExpr("vec_id AS qid", "embedding AS qvec"), 1, 32).first()
    assert hit.vec_id == 7 and hit.dist == 0


def test_shuffled_search_and_generations(spark, native, monkeypatch):
    emb, q = native
    truth = E.exact_knn(emb, q, 10).persist()
    index = build_index(emb.where("vec_id % 3 = 0"), Params(64), shards=3)
    for i in range(I.MOST_GENERATIONS + 2):
        index = insert_batch(index, emb.where(f"vec_id % 3 != 0 AND vec_id % {I.MOST_GENERATIONS + 2} = {i}"))
    assert len(index.generations) <= I.MOST_GENERATIONS and index.rows.count() == emb.count()
    again = Index.open(spark, index.path)
    want = [tuple(r) for r in again.search(q, 10, 96).orderBy("qid", "rank").collect()]
    monkeypatch.setattr(I, "MOST_READS", 0)
    assert [tuple(r) for r in index.search(q, 10, 96).orderBy("qid", "rank").collect()] == want
    assert M.recall_at_k(index.search(q, 10, 96), truth, 10).first()[0] >= 0.95
    monkeypatch.setattr(I, "MOST_READS", 8)
    monkeypatch.setattr(I, "SENT_FLOATS", 64 * 2)
    assert sorted(tuple(r) for r in index.search(q, 10, 96).collect()) == sorted(want)


def test_pending_edges_wait_in_the_shards(spark, small):
    corpus = C.doc_vec(spark, small, 64).persist()
    half = build_index(corpus.where("vec_id % 2 = 0"), Params(64))
    held = insert_batch(half, corpus.where("vec_id % 4 = 1"), verify=False)
    assert held.pending().count() > 0 and held.size_report().where("part = 'pending'").first().bytes > 0
    done = insert_batch(held, corpus.where("vec_id % 4 = 3"))
    assert done.pending().count() == 0 and done.edges().where("origin = 'screen'").count() > 0


@pytest.mark.parametrize("kind", ["pq", "aniso", "scalar"])
def test_quantised_tables(native, kind):
    emb, q = native
    truth = E.exact_knn(emb, q, 10).persist()
    index = Z.build_quantised(emb, kind, nlist=8, parts=16)
    all_cells = M.recall_at_k(index.search(q, 10, 8), truth, 10).first()[0]
    two_cells = M.recall_at_k(index.search(q, 10, 2), truth, 10).first()[0]
    assert all_cells >= 0.7 and two_cells <= all_cells


def test_direction_weighted_loss_lowers_its_own_error():
    x = np.random.default_rng(1).normal(size=(500, 16))
    c = np.zeros((1, 16))
    plain, aniso = (Z.Coder(k, c, parts=4, eta=6.0).fit(x) for k in ("pq", "aniso"))

    def along(coder):
        _, codes, _, _ = coder.encode(x)
        got = np.concatenate([coder.books[j][codes[:, j]] for j in range(4)], axis=1)
        return (((x - got) * x).sum(axis=1) ** 2 / (x**2).sum(axis=1)).mean()

    assert along(aniso) < along(plain)


def test_scalar_codes_are_nearly_unbiased():
    rng = np.random.default_rng(2)
    x, q = rng.normal(size=(400, 64)), rng.normal(size=64)
    coder = Z.Coder("scalar", np.zeros((1, 64)), bits=4).fit(x)
    _, codes, norm, factor = coder.encode(x)
    error = coder.estimate(q, 0, codes, norm, factor) - ((x - q) ** 2).sum(axis=1)
    assert abs(error.mean()) < 1.0 and error.std() < 6


def test_vector_files(spark, native, tmp_path):
    emb, _ = native
    x = np.arange(12, dtype=np.float32).reshape(4, 3)
    path = tmp_path / "x.fvecs"
    path.write_bytes(S.to_fvecs(x))
    assert (S.parse_fvecs(path.read_bytes()) == x).all()
    spark.dataSource.register(S.VectorFileSource)
    rows = spark.read.format("vecfile").option("path", str(path)).option("parts", "3").load().orderBy("vec_id").collect()
    assert [r.vec_id for r in rows] == [0, 1, 2, 3] and rows[2].embedding == [6.0, 7.0, 8.0]
    assert [r.embedding for r in S.read_fvecs(spark.read.format("binaryFile").load(str(path))).collect()] == x.tolist()
    half = S.unpack(S.pack(emb, half=True), half=True)
    assert half.join(emb.withColumnRenamed("embedding", "e"), "vec_id").where("exists(zip_with(embedding, e, (a, b) -> abs(a - b)), d -> d > 0.001)").isEmpty()


def test_versions(spark, tmp_path):
    root = str(tmp_path / "versions")
    assert S.latest(spark, root) is None
    S.publish(spark, root, 0, "a")
    S.publish(spark, root, 1, "b", 7)
    assert S.latest(spark, root) == {"version": 1, "path": "b", "batch": 7}


def test_empty_and_tiny_inputs(spark):
    none = spark.createDataFrame([], "vec_id bigint, embedding array<float>")
    ask = spark.createDataFrame([(1, [1.0, 0.0, 0.0, 0.0])], "qid bigint, qvec array<float>")
    assert E.exact_knn(none, ask, 3).count() == 0 and E.exact_knn(none, ask.limit(0), 3).count() == 0
    one = spark.createDataFrame([(9, [1.0, 0.0, 0.0, 0.0])], "vec_id bigint, embedding array<float>")
    assert [r.vec_id for r in build_index(one, Params(4, blocks=2)).search(ask, 3, 8).collect()] == [9]
    assert [r.vec_id for r in E.exact_knn(one, ask, 3, plan="blocks").collect()] == [9]
    bad = spark.createDataFrame([(1, [float("nan")] * 4), (2, None), (3, [1.0]), (4, [1.0] * 4)], "vec_id bigint, embedding array<float>")
    assert [r.vec_id for r in C.valid(bad, 4).collect()] == [4]


def test_pareto_speedup_and_tiers(spark):
    runs = spark.createDataFrame([("a", 0.8, 100.0), ("a", 0.9, 200.0), ("a", 0.85, 300.0), ("b", 0.8, 50.0), ("b", 1.0, 150.0)], "method string, recall double, n_exact double")
    assert M.tradeoff_curve(runs).count() == 4
    speed = {r.method: r.speedup for r in M.speedup_at(runs, 0.9, "a").collect()}
    assert speed == {"a": 1.0, "b": 2.0}
    scores = spark.createDataFrame([("s", m, v) for m, v in zip("abcdef", (1.0, 1.1, 10.0, 11.0, 100.0, 1000.0))], "criterion string, method string, score double")
    tiers = {r.method: r.tier for r in M.tier_methods(scores).collect()}
    assert tiers == {"a": 1, "b": 1, "c": 2, "d": 2, "e": 3, "f": 4}


# --- worked examples ----------------------------------------------------------------


def _overview(seed):
    """A pivot (place 0) with seven neighbours and the rim (place 8) of a working set of two; the target is the origin."""
    rng = np.random.default_rng(seed)
    g = Graph(Params(8, blocks=2, refs_per_block=8, m_links=8, work=2))
    g._room(9)
    g.size = 9
    pivot = np.eye(8, dtype=np.float32)[0]
    turn = rng.normal(size=(7, 8))
    g.x[0], g.x[1:8] = pivot, pivot + (turn / np.linalg.norm(turn, axis=1, keepdims=True) * rng.uniform(0.9, 1.6, size=(7, 1)))
    g.x[8] = np.eye(8, dtype=np.float32)[1] * rng.uniform(1.15, 1.45)
    g._set_edges(np.zeros(7, dtype=int), np.arange(1, 8), 0)
    return g


def test_overview_example():
    """Seven neighbours of a pivot: the test passes two, of which one is a false positive and waits in its ring, the other
    displaces the rim, which waits in the other ring; both come back with the distances paid, and no witness is seen."""
    target, starts = np.zeros((1, 8), dtype=np.float32), np.array([[0, 8]])
    for seed in range(4000):
        g = _overview(seed)
        d = np.linalg.norm(g.x[:9], axis=1)
        nearer = np.flatnonzero(d[1:8] < d[8]) + 1
        if len(nearer) != 1 or (d[1:8] <= d[0]).any():
            continue
        f = g._lockstep(target, 4, 9, 4, screen=True, starts=starts)
        if f.counters["n_pass"][0] == 2 and f.counters["n_fp"][0] == 1 and set(nearer) <= set(f.ids[0].tolist()) and f.visited[2][f.visited[1] == 0][0] < 0:
            break
    else:
        raise AssertionError("no geometry with these outcomes")
    count = {c: int(v[0]) for c, v in f.counters.items()}
    assert count["n_checked"] == 7 and count["n_exact"] == 2 + 2  # two members at the start, two that passed
    false = ({*f.ids[0].tolist()} - {0, 8, *nearer}).pop()
    assert d[false] >= d[8]  # passed by the test's error
    assert count["n_fp_reused"] == 1 and count["n_rounds"] == 1  # after one round it comes back, and so does the rim
    assert f.ids[0].tolist() == sorted([0, 8, int(nearer[0]), false], key=lambda i: d[i]) and np.allclose(f.dist[0], np.sort(d[[0, 8, int(nearer[0]), false]]))
    # with a rim as near as the pivot (the shift to the left) neither passes, and the screen agrees
    stat = f.visited[2][f.visited[1] == 0][0]
    near = g.adj[0, :7].astype(int)
    estimate = g._dots(target_table(target, g.refs).ravel(), np.zeros(7, dtype=int), np.arange(7)) / (d[0] * g.own[0, :7])
    a = g.length[0, :7]
    assert np.isclose(stat, (estimate - a / (2 * d[0])).max(), atol=1e-5) and sorted(near.tolist()) == list(range(1, 8))
    gate = estimate - (a * a + d[0] ** 2 - d[8] ** 2) / (2 * a * d[0])
    assert (gate >= 0).sum() == 2 and (gate - (d[8] ** 2 - d[0] ** 2) / (2 * a * d[0]) < 0).all()


def test_screen_adds_incoming_edges_that_pruning_alone_misses():
    """A target with four out-neighbours of which pruning keeps one in-edge; a search that screens what it visits finds three more."""
    g = Graph(Params(2, blocks=1, refs_per_block=64, m_links=8))
    g._room(11)
    g.size = 11
    target, outs, others = 0, np.array([1, 2, 3, 4]), {5, 6, 7}
    g.x[:11, :2] = [[0, 0], [1, 0], [1.1, 0.1], [1.2, -0.1], [1.15, 0.2], [-2, 0], [0, 2.2], [0, -2.4], [-3, 0.1], [0.1, 3.3], [0.1, -3.5]]
    links = [(1, 2), (1, 3), (1, 4), (1, 5), (1, 6), (1, 7), (2, 1), (3, 1), (4, 1), (5, 8), (6, 9), (7, 10)]
    g._set_edges(np.array([a for a, _ in links]), np.array([b for _, b in links]), 0)
    kept = g.keeps_incoming(outs, np.zeros(4, dtype=int))
    assert kept.tolist() == [True, False, False, False]  # the out-neighbours alone give one in-edge
    g.add_incoming(outs[kept], np.zeros(1, dtype=int), 1)
    # the target was not in the graph when it was searched for: its in-edge is hidden
    found = g._lockstep(g.x[:1], 10, 11, 10, gate=False, screen=True, starts=np.array([[1]]))
    _, pivot, stat = found.visited
    survivors = {int(p) for p, s in zip(pivot, stat) if s < 0 and p != target}
    assert others <= survivors and not survivors & {2, 3, 4}
    chosen = np.array(sorted(survivors - set(outs[kept].tolist())))
    g.pending = [(chosen, np.zeros(len(chosen), dtype=int), np.zeros(len(chosen)))]
    g.verify_pending()
    source, dst, _, origin = g.edges()
    into = sorted(zip(source[dst == 0].tolist(), origin[dst == 0].tolist()))
    assert [x for x in into if x[0] in (1, *others)] == [(1, 1), (5, 2), (6, 2), (7, 2)]


def test_bucketed_tables_join_without_an_exchange(spark, small):
    from vecgraph.queries.workloads import bucketed
    from vecgraph.sources.tables import load

    lines, orders = bucketed(load(spark, small, "lineitem"), "l_orderkey", 4), bucketed(load(spark, small, "orders"), "o_orderkey", 4)
    joined = lines.hint("merge").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString()
    assert joined.count() == load(spark, small, "lineitem").count()


def test_gate_is_open_without_a_rim():
    g = build(np.arange(30), np.random.default_rng(0).normal(size=(30, 8)).astype(np.float32), Params(8, blocks=2, work=16))
    f = g.search(np.zeros((1, 8), dtype=np.float32), 3, 4)
    assert f.counters["n_exact"][0] >= f.counters["n_pass"][0] > 0
    assert target_table(np.zeros((1, 8), dtype=np.float32), g.refs).shape == (1, 2, 32)


def test_word_vectors_against_a_loop_and_one_row_a_word_and_task(spark, monkeypatch):
    import hashlib
    from collections import Counter, defaultdict

    texts = ["a b c a  b", "b a", None, "", "a", "c c c c c a b", "é \U0001f600 a é b", "\n a\tb b a x y"] * 3
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").coalesce(1)
    monkeypatch.setattr(C, "load", lambda *_: docs)
    count, sums = Counter(), defaultdict(lambda: np.zeros(16))
    for text in texts:
        words = text.split(" ") if text is not None else []
        for i, word in enumerate(words):
            count[word] += 1
            for other in words[max(0, i - 2) : i] + words[i + 1 : i + 3]:
                if word and other:
                    digest = hashlib.md5(other.encode()).hexdigest()
                    sums[word][int(digest[:7], 16) % 16] += 1 - 2 * (int(digest[7], 16) % 2)
    name = lambda w: int(hashlib.md5(w.encode()).hexdigest()[:15], 16)
    for least in (1, 5):
        want = {name(w): (v / np.linalg.norm(v)).astype(np.float32) for w, v in sums.items() if count[w] >= least and v.any()}
        got = {r.vec_id: np.array(r.embedding, dtype=np.float32) for r in C.word_vec(spark, "", 16, least).collect()}
        assert got.keys() == want.keys() and all(np.allclose(got[k], want[k], atol=1e-7) for k in want)
    rows = C.word_sums(docs.select("text"), 16).collect()
    assert {r.word: r.n for r in rows} == {w: n for w, n in count.items() if w} and len(rows) == len({r.word for r in rows})


def test_words_given_out_early_and_cut_by_batches_are_added_up():
    import pyarrow as pa

    texts = pa.array([" ".join(f"w{(i * j) % 7}" for j in range(40)) for i in range(30)])
    whole, parts = C._Words(8), []
    whole.add(texts)
    for i in range(0, 30, 3):
        held = C._Words(8)
        held.add(texts.slice(i, 3))
        parts.append(held.out())
    rows = pa.Table.from_batches(parts).sort_by("word").combine_chunks().to_batches(max_chunksize=4)
    carried: list = []
    got = [b for r in [*rows, None] for b in C._word_vectors(r, 8, 1, carried)]
    want = list(C._word_vectors(pa.Table.from_batches([whole.out()]).sort_by("word").combine_chunks().to_batches()[0], 8, 1, carried)) + list(C._word_vectors(None, 8, 1, carried))
    assert pa.Table.from_batches(got).to_pylist() == pa.Table.from_batches(want).to_pylist() and sum(len(b) for b in got) == 7


def test_many_queries_to_all_shards_are_not_shuffled_to_them(spark, native, monkeypatch):
    emb, q = native
    index = build_index(emb, Params(64), shards=3)
    want = [tuple(r) for r in index.search(q, 10, 96).orderBy("qid", "rank").collect()]
    few = [tuple(r) for r in index.search(q, 10, 96, probes=2).orderBy("qid", "rank").collect()]
    monkeypatch.setattr(I, "MOST_READS", 0)
    assert [tuple(r) for r in index.search(q, 10, 96, probes=2).orderBy("qid", "rank").collect()] == few  # shuffled
    monkeypatch.setattr(I, "SENT_FLOATS", 64 * 3)
    monkeypatch.setattr(Index, "_search_shuffled", None)
    assert sorted(tuple(r) for r in index.search(q, 10, 96).collect()) == sorted(want)


def test_answers_within_a_radius_and_of_nodes_only(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(90, 8)).astype(np.float32)
    x[60:] = x[:30]
    emb = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    q = emb.selectExpr("vec_id AS qid", "embedding AS qvec")
    index = build_index(emb, Params(8, work=90), shards=2)
    every = index.search(q, 20, 90)
    assert sorted(tuple(r) for r in index.search(q, 20, 90, within=2.0).collect()) == sorted(tuple(r) for r in every.where("dist <= 2").collect())
    assert {(r.vec_id, r.rep_id) for r in index.members().collect()} == {(i, i % 60) for i in range(90)}
    alone = index.search(q, 20, 90, with_copies=False).toPandas()
    assert alone.vec_id.max() < 60 and (alone.groupby("qid").size() == 20).all() and (alone[alone["rank"] == 1].vec_id == alone[alone["rank"] == 1].qid % 60).all()


def test_groups_of_copies_do_not_hide_each_other(spark, tmp_path):
    from vecgraph.queries import workloads as W

    near, far = "a b c d e f g h i j k l m n o p", "q r s t u v w x y z"
    texts = [near] * 20 + [near + " q"] * 20 + [far] * 3
    spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i % 4 > 0)) for i in range(len(texts))], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    got = {r.members: (r.groups, r.agreement) for r in W.r03(spark, str(tmp_path)).collect()}
    assert got == {40: (1, 0.75), 3: (1, 2 / 3)}


def test_exact_distances_hold_few_vectors_in_a_task(monkeypatch):
    """The k nearest are measured again piece by piece; pieces change no bit of a distance."""
    import tracemalloc

    rng = np.random.default_rng(4)
    x, q = rng.normal(size=(2000, 512)), rng.normal(size=(256, 512))
    ids, qid = np.arange(2000), np.arange(256)
    best = lambda metric: [c.to_numpy() for b in E._best(ids, x, qid, q, 100, metric, True) for c in b.columns]
    tracemalloc.start()
    got = best("l2")
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 80 << 20  # 100 x 256 vectors of 512 doubles are 105 MB
    row, at, dist = got
    assert len(row) == 25_600 and (dist == np.sqrt(((q[row] - x[at]) ** 2).sum(axis=1))).all() and (row != at).all()
    monkeypatch.setattr(E, "MEASURED_BYTES", 1 << 30)
    assert all((a == b).all() for a, b in zip(got, best("l2")))


def test_scalar_codes_turn_a_query_once(monkeypatch):
    """Estimates from a query's turned vector are those from each turned residual; a search turns a block of queries in one product."""
    rng = np.random.default_rng(6)
    x = rng.normal(size=(900, 48)).astype(np.float32)
    made = X.Cells("scalar", np.arange(900), x, Params(48))
    v = x[3].astype(np.float64) + 0.1
    for c, mine in enumerate(made.members):
        own = made.codes[mine], made.norm[mine], made.factor[mine]
        assert np.allclose(made.coder.estimate(v, c, *own), made.coder.estimate(v, c, *own, made.coder.turn(v[None])[0]), rtol=0, atol=1e-9)
    whole = made.search(x[:30], 10, 64)
    asked = []
    monkeypatch.setattr(Z.Coder, "turn", lambda self, q, f=Z.Coder.turn: asked.append(len(q)) or f(self, q))
    assert all((a == b).all() for a, b in zip(whole, made.search(x[:30], 10, 64))) and asked == [30]


def test_raw_shards_are_written_part_by_part(spark, native, monkeypatch):
    """Tasks get rows, not a whole shard as one table; every shard has its vectors in the order of their ids, in parts of a bounded size, in one file."""
    emb, _ = native
    monkeypatch.setattr(type(emb.groupBy()), "applyInArrow", lambda *_: pytest.fail("a shard as one table"))
    monkeypatch.setattr(I, "PART_BYTES", 4 * 64 * 7)
    raw, centroids = I.raw_shards(emb, Params(64, shard_size=60))
    want = {r.vec_id: np.array(r.embedding, dtype=np.float32) for r in emb.collect()}
    by: dict[int, list[dict]] = {}
    for r in raw.collect():
        by.setdefault(r.shard, []).append(r.asDict())
    assert 1 < len(by) <= len(centroids) and len(raw.inputFiles()) == len(by)
    seen = []
    for rows in by.values():
        ids, x = I.raw_vectors(rows, 64)
        assert (np.diff(ids) > 0).all() and all((want[i] == v).all() for i, v in zip(ids.tolist(), x))
        assert sorted(r["part"] for r in rows) == list(range(-(-len(ids) // 7))) and max(len(r["ids"]) for r in rows) == 8 * min(7, len(ids))
        seen += ids.tolist()
    assert sorted(seen) == sorted(want)


def test_raw_shards_of_sparse_vectors_are_small(spark, small):
    """The zeros of hashed texts take no room on disk."""
    import os

    corpus = C.doc_vec(spark, small, 1536)
    raw, _ = I.raw_shards(corpus, Params(1536))
    size = sum(os.path.getsize(f.removeprefix("file://")) for f in raw.inputFiles())
    assert size < corpus.count() * 1536 * 4 / 2
    assert sum(len(r.ids) for r in raw.select("ids").collect()) == 8 * corpus.count()
