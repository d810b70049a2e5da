"""Staged analytics over error-bounded compressed fields, on Spark.

Kernels are pickled by value, so executors need no copy of the repository on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
