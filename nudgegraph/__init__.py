"""Spark-native engine for influence boosting on probabilistic networks.

Kernels that run in Python workers are pickled by value, so a cluster needs
nothing of this package installed on its executors.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
