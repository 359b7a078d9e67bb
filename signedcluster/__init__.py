"""Correlation clustering of sparse signed graphs, written for Spark DataFrames."""

import sys

from pyspark import cloudpickle

#: Functions of this package travel to workers by value, so executors need no copy of the repository.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
