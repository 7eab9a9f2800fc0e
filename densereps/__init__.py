"""Density clustering by stable samples and representatives, as Spark DataFrame plans.

Functions of this package travel to executors by value, so a cluster needs no copy of it.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
