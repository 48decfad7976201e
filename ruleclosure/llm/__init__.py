"""Operations of a training-data pipeline.  Nothing else in the library imports this subpackage.

Worker code is pickled by value, so executors need no copy of the package on their path.
"""

import importlib

from pyspark import cloudpickle

_WORKER_MODULES = (
    "common",
    "decontaminate",
    "simhash",
    "bloom_lm",
    "language_id",
    "suffix_dedup",
    "quartile_digest",
)


def ship_by_value() -> None:
    for name in _WORKER_MODULES:
        cloudpickle.register_pickle_by_value(importlib.import_module(f"{__name__}.{name}"))
