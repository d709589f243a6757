"""All registered queries of the temporal-graph engine and their SQL, by key."""

from __future__ import annotations

from functools import lru_cache

from .keys import Registry, internals, patterns, relational


@lru_cache(1)
def registry() -> Registry:
    r = Registry()
    for group in (patterns, internals, relational):
        group.register(r)
    return r


def queries() -> dict:
    return dict(registry().queries)


def oracle_sql() -> dict[str, str]:
    return dict(registry().sql)
