"""Spark-native engine for building and measuring cross-lingual natural-language-to-SQL benchmarks."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the executors by value, so workers need no copy of the repository.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
