"""distds: irregular data structures as batched DataFrame operations, and workloads built on them."""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # executors need no copy of this package
