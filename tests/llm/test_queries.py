"""The registered queries over the smallest tables: schemas, whole results, and the SQL twin."""

import duckdb
import pytest

from blockdelta.llm import queries

COLUMNS = {
    "op1_pii": ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans"],
    "op2_ngram_join": ["doc_id", "n_shingles", "component_id"],
    "op3_tree_bpe": ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
    "op4_ann": ["query_id", "rank", "vec_id", "score"],
    "op5_toxicity": ["doc_id", "held_out", "score", "predicted"],
    "op6_exact_dedup": ["doc_id", "keep_id", "group_size", "kept", "text_sha256"],
    "op7_secret_scan": ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
    "op8_packing": ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"],
    "op9_sharding": ["doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard"],
    "op10_url_filter": ["page_id", "host", "path", "rule", "verdict"],
}


@pytest.mark.parametrize("name", list(COLUMNS))
def test_query(spark, sf_dir, name):
    df = queries.QUERIES[name](spark, sf_dir)
    assert df.columns[: len(COLUMNS[name])] == COLUMNS[name]
    rows = df.collect()
    if name in ("op1_pii", "op2_ngram_join", "op3_tree_bpe", "op5_toxicity", "op6_exact_dedup", "op7_secret_scan", "op9_sharding"):
        assert len(rows) == spark.read.parquet(f"{sf_dir}/documents.parquet").count()
    if name in queries.ORACLE_SQL:
        duckdb.sql(f"CREATE OR REPLACE VIEW documents AS SELECT * FROM '{sf_dir}/documents.parquet'")
        found = duckdb.sql(queries.ORACLE_SQL[name])
        at = [found.columns.index(c) for c in df.columns]
        assert sorted(map(repr, map(list, rows))) == sorted(repr([r[k] for k in at]) for r in found.fetchall())
