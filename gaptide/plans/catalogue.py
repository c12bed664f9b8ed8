"""All registered queries of the library."""

from . import gapqueries, relational, workloads

QUERIES = gapqueries.QUERIES | relational.QUERIES | workloads.QUERIES
SQL = gapqueries.SQL | relational.SQL | workloads.SQL
