"""Reproducible topology maps, their baselines and measures, on Spark DataFrames."""

import sys

from pyspark import cloudpickle

# functions of this package travel to executors by value: a cluster's workers don't need it installed
cloudpickle.register_pickle_by_value(sys.modules[__name__])
