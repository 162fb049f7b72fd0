"""Queries that once made their data up read a given table."""

import duckdb
import pytest

from weft import catalogue


@pytest.mark.parametrize(
    "name, of",
    [
        ("hardness_witness", "events"), ("membership_general", "events"), ("count_schemas", "events"),
        ("block_orders", "events"),
        ("enumerate_language", "events"),
        ("examples", "events orders customer"),
        ("shuffle_words", "events"),
        ("orders_accepted_planted", "orders"),
    ],
)
def test_reads_a_table(spark, sf, name, of):
    frame = catalogue.queries()[name](spark, sf)
    con = duckdb.connect()
    for t in of.split():
        assert any(path.endswith(f"/{t}.parquet") for path in frame.inputFiles())
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    columns = sorted(frame.columns)
    theirs = con.execute(f"select {', '.join(columns)} from ({catalogue.oracle_sql()[name]})").fetchall()
    plain = lambda rows: sorted(tuple(f"{v:.6g}" if isinstance(v, float) else str(v) for v in r) for r in rows)
    assert theirs and plain(frame.select(columns).collect()) == plain(theirs)
