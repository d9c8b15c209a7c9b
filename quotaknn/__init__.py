"""Nearest-neighbour search under count constraints, on Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Functions sent to executors carry this package's code with them, so executors need no copy of it installed.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
