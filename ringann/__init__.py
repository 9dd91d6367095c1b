"""ringann: nearest-neighbour analytics on cyclic runs of hash codes, for Spark."""

import sys

from pyspark import cloudpickle

# Kernels travel inside the task closure, so executors need no installed copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
