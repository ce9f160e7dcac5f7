"""Graph patterns with path reachability on Spark.

Functions that run inside Python workers are pickled by value, so that a
cluster needs no copy of the package on its executors.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
