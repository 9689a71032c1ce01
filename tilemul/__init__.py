"""tilemul: distributed sparse matrix multiplication on Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Functions shipped to Python workers travel by value, so that executors need no
# copy of this package on their own path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
