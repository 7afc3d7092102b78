import os

import duckdb
import pytest

from privsketch.llm import queries


@pytest.fixture(scope="module")
def duck(medium):
    con = duckdb.connect()
    for name in os.listdir(medium):
        con.sql(f"CREATE VIEW {name.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{medium}/{name}')")
    return con


@pytest.mark.parametrize("key", sorted(queries.oracle_sql()))
def test_query_equals_its_sql(spark, medium, duck, key):
    got = queries.queries()[key](spark, medium).toPandas()
    want = duck.sql(queries.oracle_sql()[key]).df()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    rows = lambda x: sorted(map(tuple, x[cols].astype(object).itertuples(index=False)))
    assert rows(got) == rows(want)


#: Columns that every query returns at least.
COLUMNS = {
    "op1": "doc_id n_bytes n_tokens over_limit",
    "op2": "doc_id n_bytes payload_bytes payload_sha256 tail_crc32 media_bytes media_sha256 feature",
    "op3": "vec_id n_links component_id kept",
    "op4": "doc_id held_out n_tokens n_known train_tokens base_score score",
    "op5": "doc_id fingerprint component_id",
    "op6": "doc_id held_out score predicted",
    "op7": "doc_id start length ids_crc32 doc_tokens sequence_id offset",
    "op8": "doc_id held_out lang_pred score",
    "op9": "doc_id n_bytes n_removed n_spans kept_sha256",
    "op10": "doc_id n_tokens ids_sha256 decoded_sha256",
}


@pytest.mark.parametrize("key", sorted(queries.queries()))
def test_query_columns_and_rows(spark, small, key):
    df = queries.queries()[key](spark, small)
    assert set(COLUMNS[key.split("_")[0]].split()) <= set(df.columns)
    name, ident = ("embeddings", "vec_id") if key.startswith("op3") else ("documents", "doc_id")
    assert df.select(ident).distinct().count() == spark.read.parquet(f"{small}/{name}.parquet").count()
