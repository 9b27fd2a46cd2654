"""Registered queries of the co-presence methods and the SQL that must give the same rows."""

from __future__ import annotations

from copresence.plans.oracles import ORACLES
from copresence.plans.queries import QUERIES, flagship

__all__ = ["ORACLES", "QUERIES", "flagship"]
