"""A Spark-native engine for semantic filtering."""

import sys

from pyspark import cloudpickle

# Functions travel to Python workers with the plan, so executors need no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
