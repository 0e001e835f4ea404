"""All queries of the sketch engine, with their SQL."""

from pagesketch import queries_apps, queries_core, queries_relational

QUERIES = queries_core.QUERIES | queries_apps.QUERIES | queries_relational.QUERIES
SQL = queries_core.SQL | queries_apps.SQL | queries_relational.SQL
