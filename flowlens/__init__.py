"""Multi-level movement analytics on Spark: grid pyramids, local significance, Bloom edge filters, a space-time cube and its queries."""

import sys

from pyspark import cloudpickle

# Kernels travel with the tasks, so executors need no copy of this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
