"""Triangle estimation on edge streams, written for Spark.

Kernels that run inside Python workers are pickled by value, so executors need
neither this repository nor an installed copy of the package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
