"""The driver's contract, and every oracle on the smallest tables where it runs quickly."""

from __future__ import annotations

import duckdb
import pytest

import __spark_entry__ as entry
from chronofold.workloads.queries import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["q01_part", "q02_part", "q05_part", "q06_part", "q07_part", "q08_part", "q09_part", "q10_part", "mq5_item", "mq6_item", "layout_rows_by_chunk", "amplification_user", "q10_supp", "interval_subtract", "rollup_exposure"]


def test_contract(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).columns == ["brand", "valid_from", "valid_to"]


@pytest.mark.parametrize("name", SOME)
def test_oracle(spark, data, name):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{data}/{t}.parquet'")
    found = QUERIES[name](spark, data)
    want = c.execute(ORACLES[name])
    columns = sorted(found.columns)
    assert columns == sorted(d[0] for d in want.description)
    at = [[d[0] for d in want.description].index(x) for x in columns]
    assert sorted(tuple(str(r[x]) for x in columns) for r in found.collect()) == sorted(tuple(str(r[i]) for i in at) for r in want.fetchall())
