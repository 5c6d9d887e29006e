"""Spark-native engine that mends vector search graphs from past queries."""

import sys

from pyspark import cloudpickle

# Functions of this package travel by value, so executors need no copy of it.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
