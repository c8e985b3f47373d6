"""Exact co-mining of groups of time-windowed motifs on Spark DataFrames.

Functions that run in Python workers are shipped by value, so that workers need
no copy of this package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
