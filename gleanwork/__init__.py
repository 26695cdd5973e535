"""Spark-native refinement of web corpora: gate, extract, select, deduplicate, clean, account."""

from pyspark import cloudpickle as _cloudpickle
import sys as _sys

# Functions sent to Python workers travel by value, so executors need no copy of the package on their path.
_cloudpickle.register_pickle_by_value(_sys.modules[__name__])
