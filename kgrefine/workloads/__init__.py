"""Named workloads on the given tables: the query of each and its SQL twin."""

from __future__ import annotations


def queries() -> dict:
    from . import campaign, extras, methods, relational

    return {**methods.QUERIES, **extras.QUERIES, **campaign.QUERIES, **relational.QUERIES}


def oracle_sql() -> dict:
    from . import campaign, extras, methods, relational

    return {**methods.SQL, **extras.SQL, **campaign.SQL, **relational.SQL}
