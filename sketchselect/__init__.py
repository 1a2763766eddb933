"""Sketched feature selection and the relational surround it needs, on Spark."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the executors by value, so a worker needs no
# copy of the package on its own path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
