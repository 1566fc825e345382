"""The operators' queries against their SQL; the pipeline against a version of its own on one machine."""

import hashlib

import public_tokenizers
import pytest
import tiktoken

from floorcount.llm import byte_bpe, queries
from test_operators import brute_groups, contamination

SQL = queries.oracle_sql()
TABLES = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(SQL))
def test_equals_sql(name, compare):
    compare(queries.queries()[name], SQL[name], TABLES)


def test_token_ids(spark):
    ranks = byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    coder = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{TABLES}/documents.parquet").collect()}
    for r in queries.op5_byte_bpe(spark, TABLES).collect():
        ids = coder.encode_ordinary(texts[r["doc_id"]])
        raw = b"".join(i.to_bytes(4, "little") for i in ids)
        assert (r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) == (len(ids), hashlib.sha256(raw).hexdigest(), hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest())


def test_stages(spark, tmp_path):
    import corpus_pipeline
    import duckdb

    docs = spark.read.parquet(f"{TABLES}/documents.parquet")
    con = duckdb.connect()
    seen = []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = {r["doc_id"]: r for r in docs.collect()}
        stage(spark, docs, TABLES).write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        after = {r["doc_id"]: r for r in docs.collect()}
        seen.append(name)
        if k == 0:
            con.execute(f"CREATE VIEW documents AS SELECT * FROM '{TABLES}/documents.parquet'")
            assert set(after) == {r[0] for r in con.execute(f"SELECT doc_id FROM ({SQL['op2_quality_rules']}) WHERE kept").fetchall()}
        elif k == 1:
            con.execute("DROP VIEW documents")
            con.execute("CREATE TABLE documents AS SELECT * FROM (SELECT doc_id, text FROM read_parquet(?))", [f"{tmp_path}/0/*.parquet"])
            want = {r[0]: r[1] for r in con.execute(f"SELECT doc_id, kept_sha256 FROM ({SQL['op7_line_dedup']}) WHERE n_removed = 0 OR kept_chars > 0").fetchall()}
            got = {i: hashlib.sha256(r["text"].encode()).hexdigest() for i, r in after.items()}
            assert all(got[i] == want[i] for i in got) and all(after[i]["n_chars"] == len(after[i]["text"]) for i in got)
        elif k == 2:
            assert set(after) == {i for i, (_, c) in brute_groups({i: r["text"] for i, r in before.items()}).items() if i == c}
        elif k == 3:
            items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{TABLES}/benchmark.parquet").collect()]
            for i, r in before.items():
                n, hit, _ = contamination(r["text"], items)
                assert (i in after) == (not (hit and 20 * hit >= n))
        else:
            assert set(after) == set(before) and all(r["intact"] for r in after.values())
        if k < 4:
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert len(seen) == 5 and corpus_pipeline.run(spark, TABLES).count() == docs.count()


def test_stages_without_documents(spark, tmp_path):
    import corpus_pipeline

    docs = spark.read.parquet(f"{TABLES}/documents.parquet").limit(0)
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, TABLES).write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
    assert docs.count() == 0
