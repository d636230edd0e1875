"""Name -> query and name -> oracle SQL of every operator of the library."""

from __future__ import annotations

from . import catalog
from .operators import clean, dedup, evaluation, mixture, models, more, post, quality, relational, retrieval, tokenizer, variants  # noqa: F401
from .streaming import feedback  # noqa: F401

QUERIES, ORACLE = catalog.QUERIES, catalog.ORACLE
