"""meterpack: re-compression of already compressed meter streams, on Spark."""

import sys

from pyspark import cloudpickle

# Kernels travel to the workers inside the plan, so that a cluster needs no copy of this package on its machines.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
