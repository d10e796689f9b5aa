"""vecspark: approximate nearest-neighbour search and vector analytics on Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Functions of this package that run in Python workers travel with the task,
# so executors need no copy of the repository on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])

__version__ = "0.1.0"
