"""Geometric centralities of very large graphs, and training-data operators, on Spark."""

from __future__ import annotations

import sys

from pyspark import cloudpickle

# Functions of this package travel to the Python workers by value, so that a
# cluster needs no copy of the package on its executors.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
