"""Rectangle joins and their surroundings, native to Spark."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the executors by value, so a cluster needs no copy of it installed.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
