"""Operators of a training-data pipeline.  Nothing else in the library imports this package."""

import sys as _sys
from importlib import import_module as _import_module

from pyspark import cloudpickle as _cloudpickle

#: Modules with code that runs in Python workers: sent by value, so workers need no copy of the repository.
SHIPPED = ("bytewords", "quality", "near_copies", "pitman_yor", "url_filter", "byte_contexts", "byte_pairs", "shard_index")


def _ship() -> None:
    for name in SHIPPED:
        _cloudpickle.register_pickle_by_value(_import_module(f"{__name__}.{name}"))


_ship()
del _sys
