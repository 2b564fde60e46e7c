"""Spark-native local graph clustering: spread mass from seeds, sweep for the best cut."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the Python workers by value, so a cluster whose
# executors have no copy of the package still runs them.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
