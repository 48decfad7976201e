"""Worker code goes with the job, so executors need no copy of this package on their path."""

from __future__ import annotations

import sys

from pyspark import cloudpickle


def by_value(name: str) -> None:
    """Pickle the functions of module ``name`` by value."""
    cloudpickle.register_pickle_by_value(sys.modules[name])
