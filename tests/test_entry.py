"""The driver's contract, and a part of the catalogue against its SQL."""

import re
from pathlib import Path

import duckdb
import pytest

import __spark_entry__
from weft import catalogue

ROOT = Path(__file__).resolve().parent.parent
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_entry(spark):
    assert __spark_entry__.entry(spark).first().text.startswith("html head meta")


def test_core_stands_without_the_optional_part():
    for path in (ROOT / "weft").rglob("*.py"):
        if "llm" not in path.relative_to(ROOT).parts:
            assert not re.search(r"\bllm\b|corpus_pipeline", path.read_text()), path


def plain(rows, columns):
    return sorted(tuple(f"{v:.6g}" if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize(
    "name",
    [
        "words_pages", "precedence_conversations", "conflicts_users", "stable_pages", "multiplicities_events", "conflict_density_segments", "multiplicity_only_dims", "sample_sizes_lineitem",
        "star_users", "adjacency_pages", "partition_exact_events", "simplified_exact_conversations", "coverage_users", "compare_star_lineitem", "count_schemas", "orders_accepted_planted",
        "global_order_users", "precedence_from_rows", "range_pairs", "frequent_words", "density_cube", "shuffle_words", "schema_exact_users", "schema_is_users", "schema_exact_customers",
        "membership_holdout", "membership_benchmark", "permissiveness_users", "compare_chain_users", "chain_pages", "disjunctive_users", "exclusive_pairs_users", "words_planted", "words_sessions",
        "words_documents", "gap_users", "length_users", "block_orders", "frequent_by_projection",
    ],
)
def test_queries_equal_their_sql(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    frame = catalogue.queries()[name](spark, sf)
    columns = sorted(frame.columns)
    theirs = con.execute(f"select {', '.join(columns)} from ({catalogue.oracle_sql()[name]})").fetchall()
    assert plain(frame.select(columns).collect(), columns) == plain(theirs, columns)
