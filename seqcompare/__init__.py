"""A Spark-native engine for alignment-free comparison of sequences, and operators for training corpora."""

import sys

from pyspark import cloudpickle

# Functions go to Python workers whole, so that executors need no copy of this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
