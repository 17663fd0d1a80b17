"""All registered queries of the library, and the SQL of those that SQL can express."""

from importlib import import_module

MODULES = ("lexical", "vector", "relational", "corruption", "streams", "experiments")


def everything() -> tuple[dict, dict]:
    queries, oracles = {}, {}
    for name in MODULES:
        module = import_module(f"twinsift.catalogue.{name}")
        queries.update(module.QUERIES)
        oracles.update(module.ORACLES)
    return queries, oracles
