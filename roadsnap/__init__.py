"""Spark-native selection and matching of typical snapshots of a road network.

Kernels are shipped to the executors by value, so they also run on a session whose workers were started
without this repository on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
