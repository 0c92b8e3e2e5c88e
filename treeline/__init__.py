"""Spark-native forests with data and task parallelism, and the operators around them."""

import sys

from pyspark import cloudpickle

# functions that run in tasks are sent by value, so executors need no copy of the package
cloudpickle.register_pickle_by_value(sys.modules[__name__])
