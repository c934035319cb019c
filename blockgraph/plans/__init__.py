"""A small logical layer above the operators: what to search, where, how."""

from .search_plan import SearchPlan  # noqa: F401
