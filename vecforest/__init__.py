"""Spark-native approximate nearest-neighbour engine (quantile-code forests)."""

import sys

from pyspark import cloudpickle

__version__ = "0.1.0"

# functions of this package travel with their tasks: workers need no copy of it
cloudpickle.register_pickle_by_value(sys.modules[__name__])
