"""Densest placement on Spark: where to put a range of fixed size so that it covers the most."""

import sys

from pyspark import cloudpickle

#: Kernels go to the Python workers by value, so the executors need no installed copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
