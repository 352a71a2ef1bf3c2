"""blockwright: learn and run blocking functions for record de-duplication on Spark.

Functions handed to Python workers are shipped by value, so a cluster needs no copy
of this package on its executors.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
