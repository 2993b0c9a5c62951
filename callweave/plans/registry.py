"""Where workload modules enter their queries and the SQL that says the same."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Register f(t, spark), where t(name) gives a table of the data folder, under f's name."""

    def enter(f):
        def run(spark, sf_dir):
            from callweave.tables import load

            return f(lambda name: load(spark, sf_dir, name), spark)

        run.__name__, run.__doc__ = f.__name__, f.__doc__
        QUERIES[f.__name__] = run
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return enter
