"""Operators for preparing language-model training data.

Nothing else in the library imports this subpackage.  Its functions are shipped to the Python
workers by value, so the executors need no installed copy of it.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
