"""Registered queries against their SQL, contract columns, and the pipeline's stages."""

import duckdb
import pytest

from sparse_neighbors.llm import queries

COLUMNS = {
    "op1": "doc_id n_shingles component_id", "op2": "doc_id held_out n_tokens n_known train_tokens base_score score",
    "op3": "doc_id n_bytes payload_bytes payload_sha256 tail_crc32 media_bytes media_sha256 feature", "op4": "doc_id piece start length ids_crc32 sequence_id offset",
    "op5": "doc_id held_out score predicted", "op6": "doc_id start n_tokens ids_crc32", "op7": "vec_id n_links component_id kept", "op8": "doc_id held_out score predicted",
    "op9": "page_id host path rule verdict", "op10": "doc_id size source_size target taken",
}


@pytest.mark.parametrize("name", list(queries.QUERIES))
def test_contract_columns(spark, data, name):
    got = queries.QUERIES[name](spark, data)
    assert got.columns == COLUMNS[name.split("_")[0]].split()
    if name.startswith(("op1_", "op5", "op6", "op9", "op10")):
        table = {"op9": "pages"}.get(name.split("_")[0], "documents")
        assert got.count() == spark.read.parquet(f"{data}/{table}.parquet").count()


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_query_matches_sql(spark, data, name):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"create view {t} as select * from read_parquet('{data}/{t}.parquet')")
    got, want = queries.QUERIES[name](spark, data).toPandas(), con.execute(queries.ORACLES[name]).df()
    text = lambda df: sorted(tuple("NULL" if v is None or v != v else f"{v:.9g}" if isinstance(v, float) else str(v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False))
    assert text(got) == text(want)


def test_pipeline(spark, data):
    import corpus_pipeline
    from sparse_neighbors.llm.shared import materialize

    docs = spark.read.parquet(f"{data}/documents.parquet")
    columns, sizes = docs.columns, [docs.count()]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = materialize(stage(spark, docs, data), "stage")
        assert docs.columns == columns
        sizes.append(docs.count())
    assert sizes[0] > sizes[1] >= sizes[2] > sizes[3] > 0
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, data)
    assert packed.columns == COLUMNS["op4"].split() and packed.where("piece = 0").count() == sizes[4]
