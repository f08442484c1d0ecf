"""Spark-native inference for weighted first-order rules over partly known relations."""

import sys

from pyspark import cloudpickle

# Task functions travel by value, so that executors need no copy of this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
