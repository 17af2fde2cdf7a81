"""The registered queries and their SQL twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from .tables import alive

QUERIES: dict = {}
SQL: dict[str, str] = {}
_BUILT: dict = {}


def query(sql: str | None = None):
    """Register a query under its function's name, with its SQL twin if there is one."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f
    return add


def r9(c):
    return F.round(c, 9)


def built(spark, key: tuple, make, frames):
    """What ``make`` gave for this key in this application, as long as its written tables last.

    Start-up work (a relation, a lattice, an index) is done once for all queries over it.
    ``frames`` picks the tables of a result.
    """
    key = (spark.sparkContext.applicationId, *key)
    found = _BUILT.get(key)
    if found is None or not all(alive(df) for df in frames(found)):
        found = _BUILT[key] = make()
    return found


def already(spark, key: tuple) -> bool:
    """Whether something was built for this key in this application."""
    return (spark.sparkContext.applicationId, *key) in _BUILT
