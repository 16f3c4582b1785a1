"""Fuzzy multi-hop join discovery on Spark: name gate, value gate, weighted join graph, paths and their execution."""

import sys

from pyspark import cloudpickle

# Python workers get this package's functions by value: they need not find the package on their own path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
