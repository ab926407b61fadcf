"""rangekeep: range-aware, variance-optimal samples of very large weighted tables on Spark."""

from pyspark import cloudpickle as _cloudpickle

import sys as _sys

# Functions handed to executors travel by value, so workers need no copy of this package on their path.
_cloudpickle.register_pickle_by_value(_sys.modules[__name__])
