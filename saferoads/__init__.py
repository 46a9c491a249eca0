"""Safest point-of-interest search and safety indexes on Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Functions that run on executors travel by value, so no worker needs this package installed.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
