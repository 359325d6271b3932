"""Exact time-warp similarity search for Spark, with filter-and-refine bounds."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the executors by value, so that a
# cluster's Python workers need not have the package installed.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
