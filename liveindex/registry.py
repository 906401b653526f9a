"""Every query of the engine by name, with the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def register(name: str, oracle: str | None = None) -> Callable:
    """Puts a function of (spark, sf_dir) under a name."""

    def put(f: Callable) -> Callable:
        if name in QUERIES:
            raise ValueError(f"query {name} exists")
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def load() -> None:
    """Imports the workload modules, which register their queries."""
    import importlib
    import pkgutil

    from liveindex import workloads

    for found in pkgutil.iter_modules(workloads.__path__):
        importlib.import_module(f"liveindex.workloads.{found.name}")
