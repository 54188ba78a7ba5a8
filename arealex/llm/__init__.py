"""Operators of a training-data pipeline. Nothing outside this folder imports it."""

import sys

from pyspark import cloudpickle

# Worker processes get these functions by value, so an executor needs no copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
