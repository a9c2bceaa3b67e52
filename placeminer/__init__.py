"""placeminer: bottom-up process discovery on Spark.

Logs are multisets of activity sequences, candidates are places (pairs of activity
sets), and every public function takes and returns DataFrames unless it says *driver*.
"""

import sys

from pyspark import cloudpickle

# Kernels travel to the executors by value, so workers need no copy of this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])

__version__ = "0.1.0"
