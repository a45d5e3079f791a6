"""A Spark-native engine that finds the small, joinable part of a wide catalog that a question needs."""

import sys

from pyspark import cloudpickle

# Functions that run in Python workers travel with their code, so executors need no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
