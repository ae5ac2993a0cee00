"""All registered queries and the SQL that recomputes them from raw tables."""

from . import answers, gridqueries, trees
from .common import Registry


def build() -> Registry:
    r = Registry()
    for part in (trees, answers, gridqueries):
        part.register(r)
    return r
