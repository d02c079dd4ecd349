"""Registered queries of the library's own operators, each beside its SQL where SQL can say it."""

from corpuskit.queries import corpus, language, relational, release, streams  # noqa: F401  they register themselves
from corpuskit.queries.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
