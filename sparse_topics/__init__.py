"""Sparse topic factorisation of large non-negative count matrices on Spark."""

import sys

from pyspark import cloudpickle

# functions travel to the executors by value, so these need no copy of the package on their path
cloudpickle.register_pickle_by_value(sys.modules[__name__])
