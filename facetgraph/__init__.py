"""facetgraph: filtered vector search on Spark, with a text-corpus toolbox beside it."""

import sys

from pyspark import cloudpickle as _cloudpickle

# Kernels travel to executors by value, so a cluster needs no copy of this package.
_cloudpickle.register_pickle_by_value(sys.modules[__name__])
