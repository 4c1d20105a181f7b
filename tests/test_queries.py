"""Every query with SQL gives the rows of its SQL; the rest of the cheap ones give rows."""

from collections import Counter

import pytest

import __spark_entry__ as entry_module
from tests_oracle import connect, same
from vecgraph.queries import methods, workloads
from vecgraph.sources import corpora as C

BOOKS = entry_module.BOOKS
WITH_SQL = [(n, b.queries[n], b.sql[n]) for b in BOOKS for n in b.sql]


@pytest.fixture(scope="module")
def duck(small):
    return connect(small)


@pytest.mark.parametrize("name, query, sql", WITH_SQL, ids=[x[0] for x in WITH_SQL])
def test_oracle(spark, small, duck, name, query, sql):
    same(spark, small, query, sql, duck)


def test_entry(spark):
    rows = entry_module.entry(spark).collect()
    assert len(rows) == 50 and {"qid", "rank", "vec_id", "dist"} <= set(rows[0].asDict())


def test_directions_are_chosen_by_a_given_table(spark, small):
    assert any("embeddings" in f for f in entry_module.queries()["m03_reference_family"](spark, small).inputFiles())


def test_lateral_search_does_not_shuffle_pairs_by_their_vectors(spark, small):
    plan = entry_module.queries()["j13_lateral_top_k"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "vec_id" in plan and not any("qvec" in line for line in plan.splitlines() if "hashpartitioning" in line or "Sort " in line)


def test_stream_ranks_by_doubles(spark, tmp_path):
    # distances of 1 and up to 3e-9 more, the nearest last by id
    rows = [(0, [0.0] * 64), *[(i, [1.0, (9 - i) * 1e-5] + [0.0] * 62) for i in range(1, 9)]]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").toPandas().to_parquet(f"{tmp_path}/embeddings.parquet")
    name = "t04_stream_static_search"
    same(spark, str(tmp_path), entry_module.queries()[name], entry_module.oracle_sql()[name], connect(str(tmp_path)))


@pytest.mark.parametrize("name", ["m28_throughput_whole", "b10_plugin_whole", "b08_quantised_graph_whole", "t04_stream_static_search"])
def test_whole_searches_are_built_by_many_tasks(spark, small, duck, name, monkeypatch):
    from vecgraph.operators import index

    seen = []
    assign = index.assign_shards
    monkeypatch.setattr(methods, "WHOLE_SHARD", 16)
    monkeypatch.setattr(index, "assign_shards", lambda *a: seen.append(assign(*a)) or seen[-1])
    same(spark, small, entry_module.queries()[name], entry_module.oracle_sql()[name], duck)
    assert all(len(centroids) > 1 for _, centroids in seen) and seen


def test_names_are_unique_and_sql_has_queries():
    queries, sql = entry_module.queries(), entry_module.oracle_sql()
    assert set(sql) <= set(queries)
    assert len(queries) > 150 or entry_module.corpus_operators is None


def test_memory_searches_all_earlier_turns(spark, small):
    turn = {r.vec_id: r.turn for r in C.turn_ids(spark, small).collect()}
    ids = [r.vec_id for r in C.conv_vec(spark, small, 384).select("vec_id").collect()]
    rows = workloads.memory(spark, small).collect()
    assert all(r.turn == turn[r.qid] > turn[r.vec_id] for r in rows)
    found = Counter(r.qid for r in rows)
    earlier = {i: sum(turn[j] < turn[i] for j in ids) for i in ids}
    assert found == Counter({i: min(5, n) for i, n in earlier.items() if n})
    assert any(turn[r.vec_id] > 2 for r in rows)  # turns after the second are remembered
