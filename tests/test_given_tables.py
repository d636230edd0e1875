"""Queries that once made their data up follow the given table: fewer rows of it, another result."""

import os

import pytest

from textmill import registry

#: query, its table, rows left out.
READS = [
    ("cte_recursive", "orders", "o_orderkey % 2 = 0"),
    ("leaderboard_rank", "labels", "doc_id % 2 = 0"),
    ("lr_schedule", "documents", "doc_id < 100"),
    ("lsh_s_curve", "conversations", "conv_id % 2 = 0"),
    ("mean_ignore_null", "labels", "doc_id % 2 = 0"),
    ("param_count", "documents", "doc_id % 2 = 0"),
    # rows end
]


@pytest.mark.parametrize("name, table, left", READS)
def test_follows_its_table(spark, sf, tmp_path, name, table, left):
    for f in os.listdir(sf):
        if f != f"{table}.parquet":
            os.symlink(f"{sf}/{f}", tmp_path / f)
    spark.read.parquet(f"{sf}/{table}.parquet").filter(left).write.parquet(str(tmp_path / f"{table}.parquet"))
    full, part = (sorted(map(repr, registry.QUERIES[name](spark, d).collect())) for d in (sf, str(tmp_path)))
    assert full and part and full != part
