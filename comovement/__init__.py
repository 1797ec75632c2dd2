"""comovement: maximal subtrajectory joins over very large sets of moving points, as Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Executors get the kernels by value, so the package need not be installed on them.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
