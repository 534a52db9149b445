"""Partitioned pattern discovery and corpus preparation on Spark DataFrames.

Functions that run in Python workers are pickled by value, so a job works on
executors that have no copy of this package on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
