"""Attribution of byte excerpts to flows over digested payload logs, on Spark."""

import sys

from pyspark import cloudpickle

# Kernels travel to the executors by value, so workers need not have the package installed.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
