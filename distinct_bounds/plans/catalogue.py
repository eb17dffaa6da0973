"""Named queries of the engine and their SQL twins."""

from __future__ import annotations

from distinct_bounds.plans import workloads


def queries():
    return dict(workloads.QUERIES)


def oracle_sql():
    return dict(workloads.SQL)


flagship = workloads.flagship
