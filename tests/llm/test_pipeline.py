"""The pipeline against its parts, and its effect on planted rows."""

import pytest

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = [docs]
    for _, f in cp.STAGES:
        docs = f(spark, docs, SF).persist()
        out.append(docs)
    return out


def test_stages_keep_columns(stages):
    for df in stages[1:-1]:
        assert df.columns == stages[0].columns


def test_decisions_take_effect(spark, stages):
    from fieldmr.llm.decontam import contamination
    from fieldmr.llm.neardup import near_duplicates

    raw, calm, single, clean, mixed, tokens = stages
    assert calm.count() <= raw.count()
    assert single.count() == calm.select("doc_id").count() - near_duplicates(calm).where("not kept").count()
    assert near_duplicates(single).where("not kept").count() == 0
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    assert contamination(clean, bench).where("size(spans) > 0").count() == 0
    assert clean.count() == single.count() - contamination(single, bench).where("size(spans) > 0").count()
    assert tokens.count() == mixed.count()


def test_run_equals_stages(spark, stages):
    import corpus_pipeline as cp

    want = sorted(tuple(r) for r in stages[-1].collect())
    assert sorted(tuple(r) for r in cp.run(spark, SF).collect()) == want


@pytest.mark.parametrize("name", ["op1_decontamination", "op2_line_frequency", "op9_suffix_dedup", "op10_near_duplicates"])
def test_queries_match_sql(spark, duck, name):
    from fieldmr.llm import catalog

    got, want = catalog.queries()[name](spark, SF).toPandas(), duck.sql(catalog.oracle_sql()[name]).df()
    rows = lambda df: sorted(map(tuple, df[sorted(df.columns)].astype(object).values.tolist()), key=repr)
    assert rows(got) == rows(want)
