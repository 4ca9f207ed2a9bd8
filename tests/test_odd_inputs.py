"""Queries against DuckDB on small tables of odd rows."""

import duckdb
import pytest

from gnnspark.queries import registry


@pytest.fixture
def agree(spark, same, tmp_path):
    """Writes tables given as (rows, schema) to a folder and compares a query there with its SQL."""

    def check(name, **tables):
        con = duckdb.connect()
        for table, (rows, schema) in tables.items():
            spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/{table}.parquet")
            con.sql(f"create view {table} as select * from '{tmp_path}/{table}.parquet/*.parquet'")
        same(registry.queries()[name](spark, str(tmp_path)), con.sql(registry.oracles()[name]))

    return check


def test_features_of_texts_shorter_than_a_gram(agree):
    texts = [None, "", "a", "ab", "ÄÖ", "abc", "ÄÖÜ", "a\U0001f600b", "abcabc"]
    agree("feat_docs", documents=(list(enumerate(texts)), "doc_id long, text string"))
