"""All registered queries of the library and their SQL."""

from __future__ import annotations

from . import experiments  # noqa: F401  (adds its queries to those of the methods)
from .operators import relational
from .queries import ORACLE_SQL as _methods_sql
from .queries import QUERIES as _methods
from .queries import flagship  # noqa: F401
from .streaming import queries as streams

QUERIES = {**_methods, **relational.QUERIES, **streams.QUERIES}
ORACLE_SQL = {**_methods_sql, **relational.ORACLE_SQL, **streams.ORACLE_SQL}
