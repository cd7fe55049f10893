"""Differentially private stream aggregation and training-data operators on Spark."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to Python workers by value, so that executors need no
# copy of it on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
