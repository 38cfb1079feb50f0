"""Influence-aware group recommendation over item streams, written for Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Kernels that run in Python workers travel with their task, so executors need no copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
