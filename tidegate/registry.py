"""Every query of the library by name, with its DuckDB twin where SQL can express it."""

from __future__ import annotations

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    """Decorator: registers a callable (spark, sf_dir) -> DataFrame, and its SQL twin."""

    def put(f):
        if name in QUERIES:
            raise ValueError(f"two queries named {name}")
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return put


def _load() -> None:
    from tidegate.plans import suite  # noqa: F401  registers on import


def queries() -> dict:
    _load()
    return QUERIES


def oracle_sql() -> dict[str, str]:
    _load()
    return ORACLES
