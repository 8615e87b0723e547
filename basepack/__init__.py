"""basepack: learned, lossless compression of small-alphabet sequences as DataFrame operators."""

import sys

from pyspark import cloudpickle

# Kernels travel to executors by value, so executors need no copy of the package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
