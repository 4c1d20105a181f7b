"""The pipeline against a plain version of its five stages."""

import hashlib

import pytest

import corpus_pipeline
from test_operators import ODD, SCHEMA, brute_classes, brute_contaminated, brute_fingerprint, brute_quality
from vecgraph.llm import pii
from vecgraph.llm.common import read_table


@pytest.fixture(scope="module")
def result(spark, small):
    return corpus_pipeline.run(spark, small).collect()


def test_pipeline_against_brute_force(spark, small, result):
    import public_tokenizers
    from tokenizers import Tokenizer

    rows = {r.doc_id: r.text for r in read_table(spark, small, "documents").collect()}
    measured = {d: brute_quality(t) for d, t in rows.items()}
    rows = {d: t for d, t in rows.items() if measured[d][0] >= 50 and 100 * measured[d][4] <= 50 * measured[d][0]}
    prints = {d: brute_fingerprint(t) for d, t in rows.items()}
    classes = brute_classes(set(prints.values()))
    least = {}
    for d, p in prints.items():
        least[classes[p]] = min(d, least.get(classes[p], d))
    rows = {d: rows[d] for d in least.values()}
    items = [r.text for r in read_table(spark, small, "benchmark").collect()]
    rows = {d: t for d, t in rows.items() if not any(brute_contaminated(t, i) for i in items)}
    assert sorted(r.doc_id for r in result) == sorted(rows)
    tokenizer = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for r in result:
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, r.ids)).encode()).hexdigest()
        text = tokenizer.decode(r.ids, skip_special_tokens=False)
        assert r.decoded_sha256 == hashlib.sha256(text.encode()).hexdigest() and r.n_tokens == len(r.ids)
        assert not pii.base_spans(text)
        assert text == rows[r.doc_id] or "[" in text


def test_stages_keep_columns_and_take_odd_rows(spark, tmp_path):
    df = spark.createDataFrame(ODD, SCHEMA)
    spark.createDataFrame([(1, None)], "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    for rows in (df, df.limit(0)):
        docs = rows
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, rows, str(tmp_path))
            if name != corpus_pipeline.STAGES[-1][0]:
                assert out.columns == df.columns
            out.collect()
            docs = out
        assert docs is not None
