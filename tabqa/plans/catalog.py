"""All named plans of the library."""

from __future__ import annotations

from tabqa.plans import answers, files, methods, relational, streams  # noqa: F401
from tabqa.plans.answers import flagship
from tabqa.plans.registry import PLANS, SQL

__all__ = ["PLANS", "SQL", "flagship"]
