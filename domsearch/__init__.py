"""Spark-native containment search over very large, skewed collections of value sets."""

import sys

from pyspark import cloudpickle

# Executors get functions of this package themselves, so they need no copy of it.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
