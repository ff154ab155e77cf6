"""Semantic ranking on Spark: order rows by a natural-language criterion under a money budget."""

import sys

from pyspark import cloudpickle

# functions that run on executors travel by value: the package need not be installed there
cloudpickle.register_pickle_by_value(sys.modules[__name__])
