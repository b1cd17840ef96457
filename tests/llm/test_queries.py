"""Registered queries against their twins, the whole pipeline against its stages, and lost state."""

import pytest
from compare import SMALL, same

from avcurate.llm import queries


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_twin(spark, duck, name):
    same(spark, duck, queries.QUERIES[name], queries.ORACLES[name], SMALL)


def test_pipeline(spark):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    seen = {r.doc_id for r in docs.collect()}
    cur = docs
    for name, f in p.STAGES[:-1]:
        out = f(spark, cur, SMALL)
        assert out.columns == docs.columns, name
        cur = p.stage(out, "test")
        now = {r.doc_id for r in cur.select("doc_id").collect()}
        assert now <= seen and len(now) > 150
        seen = now
    packed = p.STAGES[-1][1](spark, cur, SMALL)
    a = sorted(map(tuple, packed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens").collect()))
    assert {r[0] for r in a} == seen
    b = sorted(map(tuple, p.run(spark, SMALL).select("doc_id", "start", "length", "ids_crc32", "doc_tokens").collect()))
    assert a == b


def test_pipeline_of_odd_rows(spark, tmp_path):
    """Null texts and ids, repeated ids, columns of names that are used inside, and an empty table."""
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    odd = spark.createDataFrame([(None, "ein Satz ohne Nummer", "de", "s", 20), (3, None, "en", "s", None), (3, "", "en", "s", 0), ((1 << 53) + 1, "7 8 9", None, None, 5)], docs.schema)
    for name, some in (("odd", docs.unionByName(odd).unionByName(docs.limit(20))), ("empty", docs.limit(0))):
        rows = some.selectExpr("*", "1 AS rid", "'x' AS left", "2.5 AS component", "array(1) AS h")
        rows.write.parquet(f"file://{tmp_path}/{name}/documents.parquet")
        cur = spark.read.parquet(f"file://{tmp_path}/{name}/documents.parquet")
        for stage_name, f in p.STAGES[:-1]:
            out = f(spark, cur, f"file://{tmp_path}/{name}")
            assert out.columns == rows.columns, stage_name
            cur = p.stage(out, "test")
        kept = cur.collect()
        assert all(r.text is not None and r.rid == 1 and r.left == "x" and r.h == [1] for r in kept)
        assert (len(kept) > 100) == (name == "odd") and len(kept) < 205
        p.run_to(spark, f"file://{tmp_path}/{name}", f"file://{tmp_path}/{name}-out")
        assert {r.doc_id for r in spark.read.parquet(f"file://{tmp_path}/{name}-out").collect()} == {r.doc_id for r in kept}
