"""Semiring sparse-product engine for Spark.

Sparse matrices and graphs are typed DataFrames; products over arbitrary
semirings, block formats, cost measures and the workloads built on them are
declarative Spark plans, with Arrow kernels where a plan cannot say it.
"""

import sys

from pyspark import cloudpickle

# Functions sent to executors travel by value, so that a cluster needs no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
