"""Spark-native engine for scheduling and analysing multi-adapter fine-tuning."""

import sys

from pyspark import cloudpickle

__version__ = "0.1.0"

# Functions go to Python workers by value, so that executors need not have this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
