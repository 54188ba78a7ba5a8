"""Similarity search over text-tagged rectangles, written for Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Worker processes get the package's functions by value, so an executor needs no copy of it.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
