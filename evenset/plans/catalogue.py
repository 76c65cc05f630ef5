"""Queries of the library and their SQL."""

from __future__ import annotations

from ..streaming import events
from . import methods, relational
from . import experiments as experiments  # these register their queries
from . import extras as extras
from . import studies as studies
from . import surface as surface


def queries() -> dict:
    related = {k: relational.spark_query(a) for k, (a, _) in relational.statements().items()}
    return methods.Q | related | events.Q


def oracle_sql() -> dict[str, str]:
    return methods.SQL | {k: relational.duck_text(k, b) for k, (_, b) in relational.statements().items()} | events.SQL
