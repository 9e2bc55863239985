"""Spark-native rank-revealing factorizations of matrices built from tables."""

import sys

from pyspark import cloudpickle

# Python workers may not have this package on their path: its functions travel by value.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
