"""Registered queries over the given tables, and SQL that any engine can run for the same rows."""

from . import batch, models, more

QUERIES = {**batch.QUERIES, **more.QUERIES, **models.QUERIES}
SQL = {**batch.SQL, **more.SQL, **models.SQL}
