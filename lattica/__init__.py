"""Multilevel graph clustering on Spark DataFrames.

Functions shipped to Python workers are pickled by value, so executors need
only the public packages, not this repository, on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
