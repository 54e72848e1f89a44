"""Workloads: derived tables, questions, candidates, and the registered queries with their SQL twins."""

from importlib import import_module

MODULES = ["record_queries", "profile_queries", "finance_queries", "index_queries", "serve_queries", "operator_queries", "experiments", "tool_queries"]


def load_all() -> None:
    for m in MODULES:
        import_module(f"{__name__}.{m}")
