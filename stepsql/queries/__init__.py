"""Registry of queries over the given tables, with the SQL that DuckDB can check them by."""

from . import bank_queries, core, experiments, logs, measures, operators, stream_queries  # noqa: F401
from .registry import ORACLE_SQL, QUERIES  # noqa: F401
