"""Exact density-based clustering on Spark DataFrames.

The package is pickled by value into Python workers, so executors need no
installed copy of it and no PYTHONPATH of their own.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
