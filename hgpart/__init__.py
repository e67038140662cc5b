"""Balanced hypergraph and graph partitioning on Spark DataFrames.

Functions of this package that run inside Python workers travel with the
query (pickled by value), so executors need no copy of the package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])

__version__ = "0.1.0"
