"""Code that runs in Python workers is sent by value: executors need no copy of the library."""

from __future__ import annotations

import sys

from pyspark import cloudpickle


def shipped(module: str) -> None:
    """Marks a module, by name, whose functions go to workers."""
    cloudpickle.register_pickle_by_value(sys.modules[module])
