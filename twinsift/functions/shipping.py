"""Makes Python functions of this package run on executors that have no copy of it."""

import sys

from pyspark import cloudpickle


def by_value(module_name: str) -> None:
    """Functions of the named module travel inside the task, not as an import."""
    cloudpickle.register_pickle_by_value(sys.modules[module_name])


by_value(__name__)
