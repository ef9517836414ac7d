"""Named queries over the given tables, with SQL for comparison."""

from . import graphs, operators, search, workload


def queries() -> dict:
    return graphs.QUERIES | search.QUERIES | workload.QUERIES | operators.QUERIES


def oracle_sql() -> dict:
    return graphs.SQL | search.SQL | workload.SQL | operators.SQL
