"""Raster-run spatial joins on Spark.

Kernels run inside Arrow-batched tasks.  The package pickles its own functions
by value, so executors need only the public libraries, not this package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
