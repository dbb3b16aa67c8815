"""Registered queries: ``name -> (function of (spark, sf_dir), SQL or None)``."""

from __future__ import annotations

from . import base, events, graphs, layers, models, operators, streams

ALL = {**graphs.QUERIES, **layers.QUERIES, **events.QUERIES, **operators.QUERIES, **streams.QUERIES, **models.QUERIES}


def _alone(f):
    """A query that derives all that it needs from the given tables, whatever ran before it in this session."""

    def run(spark, sf_dir):
        base.forget()
        return f(spark, sf_dir)

    return run


def queries() -> dict:
    return {k: _alone(f) for k, (f, _) in ALL.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in ALL.items() if s}
