"""Optimal search trees, and the block-parallel dynamic programs that find them, on Spark."""

import sys

from pyspark import cloudpickle

# Python workers of a cluster need not have this package installed: functions of it travel by value.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
