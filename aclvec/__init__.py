"""Access-aware vector partitioning and search on Spark.

Functions handed to Spark's Python workers are pickled by value, so that the
executors need not have this package installed.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
