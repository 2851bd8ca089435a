import pytest
from conftest import same_rows

from pacedfl.queries import ORACLE, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_query_equals_sql(spark, duck, small, name):
    assert same_rows(QUERIES[name](spark, small).toPandas(), duck.sql(ORACLE[name]).df())


def test_entry_and_registry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_approximate_topk_is_near_exact(spark, small):
    exact, near = QUERIES["topk_global"](spark, small), QUERIES["topk_approx"](spark, small)
    a, b = ({(r.client_id, r.param_idx) for r in d.collect()} for d in (exact, near))
    assert len(a & b) / len(b) > 0.9


@pytest.mark.parametrize("name, rounds", [("link_profile_gaussian", 1), ("link_profile_per_round", 10)])
def test_drawn_links_are_those_of_a_table(spark, small, name, rounds):
    """Every customer has a link, in every round; none is made up."""
    got, customers = QUERIES[name](spark, small), spark.read.parquet(f"{small}/customer.parquet")
    assert got.count() == rounds * customers.count()
    assert got.join(customers, got.client_id == customers.c_custkey, "left_anti").isEmpty()
