"""Grouped matrix multiplication, its baselines, cost model and workloads on Spark DataFrames."""

import sys

from pyspark.cloudpickle import register_pickle_by_value

# Functions of this package travel to the executors by value, so a cluster needs no copy of it.
register_pickle_by_value(sys.modules[__name__])
