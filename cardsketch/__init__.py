"""Distinct counting with small mergeable sketches, built on Spark DataFrames.

Python functions that run on executors are pickled by value, so workers need not have this
repository on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
