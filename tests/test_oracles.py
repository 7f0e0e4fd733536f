"""Every query that has a SQL twin gives its rows on the smallest tables."""

import pytest

from compare import duck_rows, spark_rows
from conftest import SF
from dnfblock.queries import catalogue

QUERIES, SQL = catalogue.queries(), catalogue.oracle_sql()


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, duck, name):
    assert spark_rows(QUERIES[name](spark, SF)) == duck_rows(duck, SQL[name])


@pytest.mark.parametrize("name", ["idx_metaphone_part", "labelled_negatives_p1", "learn_sequential_p1", "learn_semi_p1", "generate_training_customer", "field_similarity_p1", "schema_map_p5"])
def test_query_without_sql_runs_twice_alike(spark, name):
    first = spark_rows(QUERIES[name](spark, SF))
    assert first == spark_rows(QUERIES[name](spark, SF)) and first[0]


def test_entry_is_one_row(spark):
    import __spark_entry__

    row = __spark_entry__.entry(spark).collect()
    assert len(row) == 1 and row[0]["pc"] > 0.5 and row[0]["rr"] > 0.9
