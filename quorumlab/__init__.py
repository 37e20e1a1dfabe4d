"""A Spark-native engine for studying local training whose rounds end at a quorum.

Functions of this package that run inside Python workers are shipped by value, so an
executor needs no copy of the package on its own path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
