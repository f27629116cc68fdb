"""Exact point-to-point distance engine for large undirected graphs on Spark."""

import sys

from pyspark import cloudpickle

# Functions that run on executors travel by value, so executors need no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
