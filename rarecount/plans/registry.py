"""All registered queries and their SQL."""

from __future__ import annotations

from . import queries as _queries
from . import experiments, surroundings  # noqa: F401  register the experiments and the operators around the methods

queries = _queries.queries
oracle_sql = _queries.oracle_sql
flagship = _queries.flagship
