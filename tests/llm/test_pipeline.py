"""The pipeline's stages against the operators' own brute-force rules, and its queries against their SQL."""

import duckdb
import pytest

import corpus_pipeline
from crowdlink.llm import registry
from tests.llm.test_operators import contaminated, shingle_classes
from tests.test_queries import rows_of

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, kept = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, SF).collect(), docs.schema)
        assert docs.columns == columns
        kept[name] = {r.doc_id: r.text for r in docs.collect()}
    before = sorted(kept["line_dedup"])
    classes = shingle_classes([kept["line_dedup"][k] for k in before])
    assert sorted(kept["near_dedup"]) == [before[k] for k, c in enumerate(classes) if k == c]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    for k, text in kept["near_dedup"].items():
        n, hit, _ = contaminated(text, items)
        assert len(kept["decontamination"][k]) < len(text) if hit else kept["decontamination"][k] == text
    assert corpus_pipeline.run(spark, SF).count() == len(kept["decontamination"])


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in "documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    df = registry.QUERIES[name](spark, SF)
    r = con.execute(registry.ORACLES[name])
    assert rows_of(df.columns, [tuple(x) for x in df.collect()]) == rows_of([c[0] for c in r.description], r.fetchall())
