"""Proximity-graph merging and vector search on Spark DataFrames."""

import sys

from pyspark import cloudpickle

__version__ = "0.1.0"

# Kernels travel to the executors with the plan; the package need not be installed there.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
