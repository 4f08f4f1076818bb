"""The estimator, and the registered queries."""


def load_queries() -> None:
    """Import all modules that register queries."""
    from . import queries_method, queries_relational, queries_streams, queries_workloads  # noqa: F401
