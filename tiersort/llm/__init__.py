"""Operators for preparing large text corpora.

Nothing outside this subpackage (and ``corpus_pipeline.py``) imports it.
Workers get its functions by value, so a cluster's executors do not need the
repository on their path.
"""

import importlib
import pkgutil

from pyspark import cloudpickle


def _ship_by_value() -> None:
    for found in pkgutil.iter_modules(__path__):
        cloudpickle.register_pickle_by_value(importlib.import_module(f"{__name__}.{found.name}"))


_ship_by_value()
