"""Exact fixed-radius near-neighbour graphs on Spark."""

import sys

from pyspark import cloudpickle

# Arrow kernels travel by value, so workers need no copy of the package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
